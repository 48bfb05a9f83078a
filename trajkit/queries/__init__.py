"""Registered queries by area, each beside its independent SQL."""
