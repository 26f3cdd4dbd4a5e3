"""packgraph: bit-economical graph storage and graph algorithms on Spark DataFrames."""
