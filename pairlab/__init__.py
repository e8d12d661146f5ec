"""Post-training data, rewards and evaluation on pairs of code before and after a fix, for Spark."""
