"""Part of the engine: baselines."""
