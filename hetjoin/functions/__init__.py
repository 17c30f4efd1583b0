"""Coordinates, measures, profiles and user-defined functions."""
