"""The methods' operators on DataFrames."""
