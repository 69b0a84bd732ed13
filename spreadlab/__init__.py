"""spreadlab: influence-spread estimation and corpus operators on Spark DataFrames."""
