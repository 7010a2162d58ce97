"""How a message becomes a join: reads, join shapes, access paths, placement, replicas."""
