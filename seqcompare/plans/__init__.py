"""Physical plans for all pairs, their choice, and whole pipelines from a configuration."""
