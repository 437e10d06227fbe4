"""patchflow: the data side of codec-driven streaming perception, on Spark."""
