"""Tables, experiment mappings and their features."""
