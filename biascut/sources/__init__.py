"""Edge sources and sinks, and the workload graphs built from the shared tables."""
