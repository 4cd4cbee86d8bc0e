"""Tables, fixtures of items and demand, generators, and storage of codebooks."""
