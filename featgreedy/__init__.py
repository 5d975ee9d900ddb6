"""Feature-distributed greedy regression and its data plumbing, written for Spark."""
