"""Recognising when columns of different tables measure the same variable, from their values, on Spark."""
