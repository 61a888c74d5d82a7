"""Measures, on Spark, how much of a token's spelling its vector gives away and what puts it there."""
