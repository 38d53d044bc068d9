"""Matrix operators: DataFrames of tiles in, DataFrames of tiles out."""
