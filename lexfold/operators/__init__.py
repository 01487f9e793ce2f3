"""Plan-building operators on DataFrames."""
