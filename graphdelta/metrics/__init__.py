"""Counters, times and relative measures."""
