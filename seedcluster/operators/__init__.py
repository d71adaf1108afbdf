"""Operators on graphs, motifs, models and clusters."""
