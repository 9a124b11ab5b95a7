"""Operators of a training-data pipeline: chat, tokens, filters, near copies."""
