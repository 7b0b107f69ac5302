"""Tables, graph builders, generators and file formats."""
