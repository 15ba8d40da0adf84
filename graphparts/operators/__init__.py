"""Graph and matrix operators."""
