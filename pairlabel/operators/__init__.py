"""DataFrame operators: workloads, easy labels, features, inference, baselines, measures."""
