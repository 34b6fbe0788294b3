"""Sorted-window entity resolution for Spark."""
