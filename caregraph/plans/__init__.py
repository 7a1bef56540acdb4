"""plans of the event-graph engine."""
