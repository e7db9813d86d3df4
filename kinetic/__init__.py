"""Speed-partitioned analytics of linearly moving objects on Spark."""
