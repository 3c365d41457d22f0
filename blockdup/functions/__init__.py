"""Column-level building blocks: lexing, similarity algebra, global orders, filters."""
