"""Typed answers, their claims, checks against the trace, and the gate."""
