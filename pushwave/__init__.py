"""Approximate personalized PageRank and companions, expressed as Spark plans."""
