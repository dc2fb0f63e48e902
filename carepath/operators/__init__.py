"""DataFrame operators: what is computed from visits, codes, notes and trajectories."""
