"""Tables with their declared keys, workload files, result sinks and layouts."""
