"""Streaming forms of the map, the fan-out, the folded gradient and event windows."""
