"""Options and the planner of searches."""
