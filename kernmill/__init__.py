"""Exact kernel k-means for Spark: kernels, layouts, engines, costs, measures and streams."""
