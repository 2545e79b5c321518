"""Snapshots from streams of points."""
