"""caregraph: a PySpark-native clinical event-graph engine."""
