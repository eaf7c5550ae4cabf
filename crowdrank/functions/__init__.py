"""Part of the engine; see the module names."""
