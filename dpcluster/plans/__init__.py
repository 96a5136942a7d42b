"""Error models, the planner between methods, relational helpers and experiments."""
