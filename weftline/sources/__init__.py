"""Tables and files as DataFrames, and back."""
