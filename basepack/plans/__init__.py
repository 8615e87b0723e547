"""Model and codec plans, measures, experiments."""
