"""Local moving, contraction and the multi-level driver."""
