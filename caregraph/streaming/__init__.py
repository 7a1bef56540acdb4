"""streaming of the event-graph engine."""
