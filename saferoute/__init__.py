"""Obstacle-avoiding routing over road networks, expressed as Spark DataFrame programs."""
