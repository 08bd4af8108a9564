"""Query language, translation to algebra, rewriting, lowering to DataFrames, workload and metrics."""
