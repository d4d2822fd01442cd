"""Ranks over windows of a stream (an extension of ours)."""
