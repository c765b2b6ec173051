"""Tables, sketch stores and simulated streams."""
