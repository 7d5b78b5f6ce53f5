"""Queries, orders, bounds, stages and rewrites: metadata on the driver, no data."""
