"""What the engine is compared with."""
