"""Schemas as values: text forms, membership and inclusion of single schemas, SQL functions."""
