"""Graph sources and sinks: given tables, edge lists, generated known-answer graphs."""
