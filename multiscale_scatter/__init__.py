"""Multi-scale scatterplot layout and serving on Spark."""
