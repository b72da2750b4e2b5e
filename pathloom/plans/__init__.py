"""Query plans: the expression algebra, comparison methods, extensions, measures, workloads, and the registry of queries."""
