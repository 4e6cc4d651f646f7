"""Ranked similarity search of spatial communities on road networks, as Spark plans."""
