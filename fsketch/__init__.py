"""fsketch: sketch-based clustering with grouped binary selection, on Spark DataFrames."""
