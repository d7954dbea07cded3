"""Tables, vectors derived from them, access policies and query workloads."""
