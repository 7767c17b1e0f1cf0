"""Tables, base relations, files."""
