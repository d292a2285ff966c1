"""Memory models, counters and scaling measures."""
