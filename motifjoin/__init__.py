"""Pattern joins over large graphs and relations, written for Spark DataFrames."""
