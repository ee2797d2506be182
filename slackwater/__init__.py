"""Deadline-driven, cost-minimising batch analytics on Spark."""
