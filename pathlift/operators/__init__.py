"""The methods, as operators over DataFrames."""
