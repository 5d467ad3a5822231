"""Loss-bounded spatio-temporal partitioning on Spark."""
