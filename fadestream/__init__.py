"""Clustering of unbounded batches whose distribution may change abruptly, on DataFrames."""
