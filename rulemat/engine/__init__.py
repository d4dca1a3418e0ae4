"""Materialisation and its maintenance under changes of rules and facts."""

from .reasoner import Config, Reasoner

__all__ = ["Config", "Reasoner"]
