"""Physical plans of the sparse product and the planner that chooses among them."""
