"""DataFrame operators of the engine: sources, partition plans, blocks, operations, measures."""
