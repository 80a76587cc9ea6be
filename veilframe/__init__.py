"""Release of numeric tables in perturbed form on Spark: methods, baselines, attacks and measures."""
