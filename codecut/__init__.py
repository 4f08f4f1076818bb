"""Distributed clustering on learned binary codes, written for the DataFrame API."""
