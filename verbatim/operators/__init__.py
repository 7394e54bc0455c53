"""Methods, baselines and measures as functions from DataFrames to DataFrames."""
