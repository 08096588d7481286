"""Tables to graphs, edge lists in files, sinks."""
