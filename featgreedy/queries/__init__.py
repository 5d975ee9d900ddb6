"""Query catalogue: one function per method, workload or operator, and its SQL."""
