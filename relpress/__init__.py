"""Compression, filtering and solving over large extensional relations, on Spark DataFrames."""
