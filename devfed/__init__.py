"""Federated learning on data that is not identically distributed across its owners, on Spark."""
