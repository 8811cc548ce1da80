"""Matrix operators: DataFrames in, DataFrames out."""
