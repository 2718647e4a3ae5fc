"""Fine-grained distributed sorting and tree merging on Spark DataFrames."""
