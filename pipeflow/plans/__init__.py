"""Flow graphs, phases, orders, memory, progress and cost: what is decided before data moves."""
