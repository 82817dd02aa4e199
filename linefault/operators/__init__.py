"""Physical building blocks: tickets, features, rates, thresholds, windows, faults, clusters, baselines, measures."""
