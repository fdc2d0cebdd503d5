"""Planning, workloads, experiments and the driver's queries."""
