"""Tables, objects with an attribute, and query workloads."""
