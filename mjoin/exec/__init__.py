"""Evaluation of trails as single jobs, merging of their outputs, and the runner of schedules."""
