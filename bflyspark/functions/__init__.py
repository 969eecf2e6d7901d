"""Column functions: intervals, priorities, portable hashes."""
