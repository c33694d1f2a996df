"""Tables, signal files and planted data."""
