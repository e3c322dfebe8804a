"""Input tables and derived vector fixtures."""
