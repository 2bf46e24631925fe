"""Plan capture, plan features and the query workloads."""
