"""Query graphs, matching orders and configurations."""
