"""Tables, stores and round trips."""
