"""Fields of view that arrive over time."""
