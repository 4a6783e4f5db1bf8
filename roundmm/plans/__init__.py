"""Round drivers, planners, cost ledgers, density estimates and rewrites."""
