"""Sampling, caching, model, exchange and measures as plans over tables."""
