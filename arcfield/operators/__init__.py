"""Zones, neighbours, regions, mesh and pyramid operators."""
