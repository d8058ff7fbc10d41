"""Packing, encoding, serializing, storing: the engine's operators."""
