"""Structured Streaming over events and over points."""
