"""Tables, edge files, graph builders, generators and sinks."""
