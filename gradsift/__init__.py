"""gradsift: meta-gradient training-data selection on Spark DataFrames."""
