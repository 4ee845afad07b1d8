"""standq: standing (continuous) relational queries on Spark."""
