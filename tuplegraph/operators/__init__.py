"""Methods on graphs, indexes, answers, clusters and measures, as functions from DataFrames to DataFrames."""
