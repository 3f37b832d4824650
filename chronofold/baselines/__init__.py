"""What the engine is held against; some of it is wrong on purpose."""
