"""Query objects, the planner and the workloads."""
