"""K-anonymous cohorts on Spark: consistent sampling, consecutive splitting, baselines, measures."""
