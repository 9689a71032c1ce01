"""Products, layouts, measures and matrix algebra over DataFrames."""
