"""commlens: community profiling over text-and-link graphs, on PySpark."""
