"""Rectangle analytics over weighted point grids, as Spark DataFrames."""
