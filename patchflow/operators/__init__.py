"""Operators: selection, canvases, sampling, clustering, curation, balance, timelines, gates."""
