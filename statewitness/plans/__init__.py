"""Registered workloads on the given tables, each with SQL that restates its result from the base tables."""
