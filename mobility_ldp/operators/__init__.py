"""The methods, as functions from DataFrames to DataFrames."""
