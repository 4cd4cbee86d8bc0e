"""Estimation, pricing and design of codebooks as operators on DataFrames."""
