"""Graph builders on tables, named graphs, readers and writers."""
