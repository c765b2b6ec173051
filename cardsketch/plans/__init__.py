"""Planning over stored sketches, relational workloads and the query registry."""
