"""Profitable, confident rules over interval timelines, as DataFrame plans."""
