"""How relational tables become facts, edges and classes."""
