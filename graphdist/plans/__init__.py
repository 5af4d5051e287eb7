"""Reading physical plans."""
