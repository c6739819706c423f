"""Ordering, candidate generation, filters, verification and the joins built from them."""
