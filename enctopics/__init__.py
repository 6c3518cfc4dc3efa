"""Topic clustering over deterministically encrypted token indexes, written for Spark."""
