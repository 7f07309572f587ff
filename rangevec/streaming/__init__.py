"""Insertion and monitoring of streams."""
