"""plans of calseries."""
