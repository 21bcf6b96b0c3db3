"""Feature tables, generators and query workloads."""
