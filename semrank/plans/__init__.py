"""Cost model, planner, simulation, measures and experiment workloads."""
