"""Driver queries, module by module."""

from __future__ import annotations

import importlib

MODULES = ("tokenizer", "hardware", "corpus", "instruct", "evaluate", "generalise", "relational", "streams")


def load():
    """The registry with all modules' queries."""
    for name in MODULES:
        importlib.import_module(f"{__name__}.{name}")
    return importlib.import_module(f"{__name__}.registry")
