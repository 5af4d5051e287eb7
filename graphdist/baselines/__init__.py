"""Labelling alternatives and search baselines."""
