"""Schedules, queues, training runs and workloads built from the operators."""
