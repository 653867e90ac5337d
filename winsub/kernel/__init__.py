"""Per-stream data structures in plain Python; Spark operators drive them."""
