"""Graphs of similar entities."""
