"""Choice of a method and of a physical pairing."""
