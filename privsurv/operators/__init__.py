"""Preparation, fitting, private mechanisms, samplers, measures."""
