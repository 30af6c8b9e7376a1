"""Mapping communicating tasks onto the processing elements of a hierarchical machine, on Spark DataFrames."""
