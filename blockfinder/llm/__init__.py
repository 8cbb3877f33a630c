"""Operators that a training-data pipeline needs, each over a whole table.

Nothing outside this folder imports it; ``registry`` lists its queries.
"""
