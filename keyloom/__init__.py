"""Keyloom: value filters and large-corpus operators on Spark DataFrames."""
