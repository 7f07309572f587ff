"""Named queries, experiments and strategy choice."""
