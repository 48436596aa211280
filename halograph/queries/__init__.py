"""Queries on the given tables, each with SQL that computes the same rows from the base tables."""
