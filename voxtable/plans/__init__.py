"""Workloads and operator queries, each registered when its module is imported."""

from importlib import import_module

MODULES = ("corpus", "speech_tokens", "rewards", "text_side", "corpus_sets", "measures", "experiments", "relational", "streams")


def register_all() -> None:
    for name in MODULES:
        import_module(f"voxtable.plans.{name}")
