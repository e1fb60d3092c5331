"""Spells, counts and scoring over streams."""
