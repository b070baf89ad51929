"""Configuration, engine, statements, measures and workloads."""
