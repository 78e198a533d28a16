"""pathsieve: path queries over property graphs with early filtering, on Spark DataFrames."""
