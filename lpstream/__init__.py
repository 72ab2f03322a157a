"""Norm-proportional row sampling over turnstile streams, on Spark."""
