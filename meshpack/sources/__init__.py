"""Tables, the mesh catalogue, and packed files."""
