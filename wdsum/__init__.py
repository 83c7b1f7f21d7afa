"""Weighted distinct sums over streams: exact answers, sketches and their measures, on Spark."""
