"""Graph sources: tables, edge lists, and the builders of the experiment graphs."""
