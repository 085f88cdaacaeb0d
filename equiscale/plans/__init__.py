"""Configuration, cost models, measures and probes."""
