"""Staging, repetition planning and pipeline profiles."""
