"""Ratings that arrive as events: windows, late rows, online updates, per-row state."""
