"""Methods of the engine: roads, relevance, index, influence, selection."""
