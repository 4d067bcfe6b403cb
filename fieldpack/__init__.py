"""fieldpack: very compact, lossy archives of time-varying scalar fields, on Spark DataFrames."""
