"""Enumeration operators over query relations."""
