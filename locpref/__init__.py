"""Recommendation of location privacy preferences at scale, plain and under local differential privacy."""
