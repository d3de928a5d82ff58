"""sources of calseries."""
