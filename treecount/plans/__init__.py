"""Templates, counting plans, estimates, costs, measures and workloads."""
