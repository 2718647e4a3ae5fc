"""Distributed operators: sorting, merging, joining and ranking."""
