"""Column functions and the UDF, UDAF and UDTF surface."""
