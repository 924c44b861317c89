"""Frames with known order and the planner over them."""
