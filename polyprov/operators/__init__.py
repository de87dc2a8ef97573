"""Annotation rules on annotated frames."""
