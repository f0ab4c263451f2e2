"""Piece forming, tree planning and the query catalog."""
