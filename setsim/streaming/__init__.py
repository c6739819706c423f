"""Similarity over streams: sets per window, probes against stored sets, an incremental index, an online index."""
