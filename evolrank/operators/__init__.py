"""Graph construction, frontier operators and layouts."""
