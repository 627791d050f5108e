"""Error-bounded compression, analysis and in-place querying of 3-D point clouds on Spark."""
