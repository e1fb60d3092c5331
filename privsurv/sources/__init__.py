"""Tables, survival workloads and planted data."""
