"""Methods of the engine: energy, shards, planner, payload, transport, loaders, receiver, measures."""
