"""Column functions on binary codes, encoders, and functions registered with SQL."""
