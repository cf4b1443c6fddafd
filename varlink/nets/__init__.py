"""Numpy networks with hand-written gradients, their losses, and the trainers."""
