"""Specs, routes and materialisation."""
