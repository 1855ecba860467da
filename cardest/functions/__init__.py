"""Column functions: portable random numbers, SQL-callable sizing, histogram functions."""
