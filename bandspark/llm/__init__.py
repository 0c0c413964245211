"""Operators of a training-data pipeline: documents in, decisions and statistics out."""
