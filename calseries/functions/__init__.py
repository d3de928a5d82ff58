"""functions of calseries."""
