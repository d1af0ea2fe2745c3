"""Exact shortest-path counting over changing graphs, built on PySpark DataFrames."""
