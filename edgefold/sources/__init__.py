"""Tables, graphs, features, edge files and sinks."""
