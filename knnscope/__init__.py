"""Density clustering of points seen through a limited nearest-neighbour interface, on Spark DataFrames."""
