"""Tables, graphs, features, and file formats."""
