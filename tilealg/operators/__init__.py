"""Matrix, graph and learning operators on DataFrames."""
