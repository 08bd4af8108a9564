"""Regular path queries over property graphs, as DataFrames."""
