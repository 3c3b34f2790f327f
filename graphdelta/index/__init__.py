"""Candidate indexes: which data vertices a pattern vertex can still map to."""
