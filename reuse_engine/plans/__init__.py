"""Named workloads and the SQL they are checked against."""
