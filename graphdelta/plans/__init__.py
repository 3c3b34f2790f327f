"""Matching orders and the telescoped terms of a change."""
