"""Tables, points and planted mixtures."""
