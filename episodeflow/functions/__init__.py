"""Scalar rules of episodes and rates, Python UDFs and the SQL surface."""
