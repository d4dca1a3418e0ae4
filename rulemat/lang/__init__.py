"""Rule language: syntax tree, parser and checks."""

from .checks import RuleError, UnstratifiableError, check_program, require_safe
from .syntax import Aggregate, Atom, Bind, Compare, Const, Program, Rule, Var, parse_atoms, parse_program

__all__ = ["Aggregate", "Atom", "Bind", "Compare", "Const", "Program", "Rule", "RuleError", "UnstratifiableError", "Var", "check_program", "parse_atoms", "parse_program", "require_safe"]
