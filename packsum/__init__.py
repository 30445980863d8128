"""Estimates of packing and scheduling optima from small mergeable summaries, as Spark plans."""
