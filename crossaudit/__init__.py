"""Audit of how well classifiers travel between differently labelled datasets, on Spark DataFrames."""
