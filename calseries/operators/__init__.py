"""operators of calseries."""
