"""Where sets come from and go to: workloads over the given tables, generators, readers and writers."""
