"""Sub-window statistics over time series, answered from caches of mergeable summaries, on Spark."""
