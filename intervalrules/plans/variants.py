"""The variants of the experiments: all give the same rules, only their cost differs."""

from __future__ import annotations

VARIANTS = {
    "full": {},
    "matrix": {"layout": "matrix"},
    "no_budget": {"class_budget": False},
    "neither": {"layout": "matrix", "class_budget": False},
    "no_symbol_removal": {"disable": frozenset({"symbols"})},
    "no_open_bound": {"disable": frozenset({"open_bound"})},
    "no_right_bound": {"disable": frozenset({"right_bound"})},
    "no_confidence_gate": {"disable": frozenset({"confidence"})},
    "no_zero_carry": {"zero_carry": False},
}
