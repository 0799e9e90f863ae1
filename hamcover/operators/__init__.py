"""Hashers, index, searches and measures."""
