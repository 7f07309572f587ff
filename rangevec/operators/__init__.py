"""Exact search, graphs, the index and its competitors."""
