"""Tables as points: bounds, stand-in workloads, readers and writers."""
