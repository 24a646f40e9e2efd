"""Matrix builders on tables, random matrices, readers and writers."""
