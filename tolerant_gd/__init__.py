"""Straggler-tolerant gradient descent over Spark DataFrames."""
