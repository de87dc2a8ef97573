"""Annotation algebras, and tools on annotation texts."""
