"""Reference-aware schema matching on Spark."""
