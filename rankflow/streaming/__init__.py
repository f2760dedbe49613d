"""Ranks maintained on streams of edge changes."""
