"""Transposition methods and what they are composed of."""
