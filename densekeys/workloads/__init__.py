"""The queries: every method, variant, baseline, measure and application on the given tables, with SQL to compare."""
