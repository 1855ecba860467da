"""The estimators that the sample is compared with: histograms, multi-column statistics, grids, synopses, Spark's own."""
