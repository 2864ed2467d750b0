"""Repository changes as streams."""
