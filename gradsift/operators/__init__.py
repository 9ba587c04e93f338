"""Sketches, recovery, losses, trainers and the relational operators around them."""
