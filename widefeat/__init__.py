"""Feature-centric wide tables on Spark."""
