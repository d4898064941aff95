"""Operator registry, pages, cost guard, plan language, static verification, execution and repair."""
