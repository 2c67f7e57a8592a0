"""Cell maps and their algebra, the engine, box counting, baselines, measures and general operators."""
