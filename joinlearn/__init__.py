"""Least-squares learning over normalised tables with Spark; see README.md."""
