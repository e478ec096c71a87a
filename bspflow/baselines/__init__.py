"""Stand-ins for the architectures that the engine is compared with; each runs rank, shortest paths and components."""
