"""Joins of two streams over large sliding windows, written for Spark."""
