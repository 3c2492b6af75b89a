"""Choice of physical strategy for the engine's own logical steps."""
