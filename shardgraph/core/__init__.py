"""The pull-window engine: rounds, scheduling and the edge cache."""
