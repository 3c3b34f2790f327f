"""Graphs from tables, update batches, and edge list readers and writers."""
