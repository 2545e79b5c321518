"""DataFrame operators on meshes, domains, arrays and streams of bytes."""
