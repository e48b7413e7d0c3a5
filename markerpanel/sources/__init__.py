"""Tables, panels, readers and writers."""
