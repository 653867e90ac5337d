"""SQL functions over texts and windows."""
