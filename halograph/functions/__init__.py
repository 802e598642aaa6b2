"""Column functions shared by the engine."""
