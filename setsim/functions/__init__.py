"""Column-level building blocks: similarity arithmetic, token sets, bitmaps, bound theory."""
