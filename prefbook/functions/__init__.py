"""Column functions: information measures, portable random numbers, SQL functions and UDFs."""
