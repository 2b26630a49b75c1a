"""Driver-side structures: queries, hypergraphs, bag trees, their rewrites, costs and the planner."""
