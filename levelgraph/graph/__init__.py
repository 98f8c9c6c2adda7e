"""Graph construction from tables and generators."""
