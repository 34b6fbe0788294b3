"""Configuration, choice of engine, and whole resolution plans."""
