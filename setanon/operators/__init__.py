"""Operators on record sets, groupings and query logs."""
