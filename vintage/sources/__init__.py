"""Tables, readers, writers and shared scratch tables."""
