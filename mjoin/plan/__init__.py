"""Join graphs, trails, covers, schedules and the planner."""
