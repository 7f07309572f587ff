"""Tables, query workloads and stored indexes."""
