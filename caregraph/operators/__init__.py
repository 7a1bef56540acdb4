"""operators of the event-graph engine."""
