"""Tables, the code index, and generated codes."""
