"""Join configuration, cost planning and measures."""
