"""Inverse similarity queries on Spark: which objects have every member of a query set in their own result."""
