"""From join queries to Spark plans."""
