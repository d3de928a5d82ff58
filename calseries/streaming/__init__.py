"""streaming of calseries."""
