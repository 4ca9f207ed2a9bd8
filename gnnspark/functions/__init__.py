"""Expressions shared by all operators."""
