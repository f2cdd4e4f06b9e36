"""Streams that keep the inputs of the methods up to date."""
