"""Edge lists and stored indexes."""
