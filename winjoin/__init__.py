"""Sliding-window stream joins on Spark: batch replay, live streams, and the measures to compare methods."""
