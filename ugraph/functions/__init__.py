"""Part of ugraph."""
