"""Functions for SQL users, and the few places where Python code runs beside the plan."""
