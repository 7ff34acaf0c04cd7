"""Queries for the driver, with their SQL."""
