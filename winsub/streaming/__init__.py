"""Live windows and standing queries on unbounded input."""
