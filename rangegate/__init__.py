"""Range-emptiness filters on Spark: prefix filters that tune themselves to the keys and a sample of empty queries."""
