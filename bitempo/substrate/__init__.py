"""Belief log, clock, versions, snapshots, replay and their checks."""
