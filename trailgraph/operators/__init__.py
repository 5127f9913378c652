"""Methods of the trail engine."""
