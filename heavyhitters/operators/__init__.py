"""Counter summaries, their merges, the competing methods and relational helpers."""
