"""Operators on events, cells, pairs, scores, members and alerts."""
