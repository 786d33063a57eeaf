"""Private spatial histograms for range counts over trajectories, on Spark."""
