"""Demand estimation and redesign on streams of requests."""
