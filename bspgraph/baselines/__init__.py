"""The engines to compare with, as methods of this engine."""
