"""Repair of functional-dependency errors that keeps frequent value combinations, set-parallel on Spark."""
