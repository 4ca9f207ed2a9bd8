"""Structured Streaming: edge arrivals, degree state, gradient queues."""
