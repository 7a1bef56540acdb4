"""sources of the event-graph engine."""
