"""Event-time windows, state and warm solves."""
