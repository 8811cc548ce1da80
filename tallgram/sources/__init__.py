"""Tables, workload matrices, files and sinks."""
