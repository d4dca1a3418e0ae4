"""Streams of facts and rules, and windows over readings."""
