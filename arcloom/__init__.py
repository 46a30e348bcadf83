"""Graph kernels and training-data operators on Spark."""
