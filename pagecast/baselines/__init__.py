"""Methods that the engine is compared with."""
