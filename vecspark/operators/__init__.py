"""Clustering, seeding, stopping, index and measure operators."""
