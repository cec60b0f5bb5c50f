"""Progressive aggregation over tables whose text needs a costly semantic function, on Spark."""
