"""Keeping a graph fresh from a stream of events."""
