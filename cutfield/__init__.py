"""Partition a discrete graphical model, then infer: cluster mean field on DataFrames."""
