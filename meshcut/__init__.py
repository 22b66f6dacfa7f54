"""Equal-load splitting of weighted point sets and meshes, on Spark DataFrames."""
