"""Tables, graphs derived from them, and generators."""
