"""Telemetry summaries, behaviour profiles and checked answers on Spark."""
