"""Samplers, metrics and neighbourhood operators on property graphs."""
