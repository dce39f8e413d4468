"""Score-partitioned approximate membership filters on Spark."""
