"""Choices above Catalyst: where matrices live and which route makes a projection."""
