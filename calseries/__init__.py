"""calseries: analytics over calendar-bound series on Spark DataFrames."""
