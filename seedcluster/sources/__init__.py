"""Tables, graphs derived from them, readers and writers."""
