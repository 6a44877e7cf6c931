"""gamat: gather/apply matrix engine on Spark DataFrames."""
