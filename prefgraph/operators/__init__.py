"""Operators on ballots, margins, graphs, paths and rules."""
