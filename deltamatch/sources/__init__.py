"""Graphs and update streams from tables, files and generators."""
