"""All queries of this subpackage and their SQL."""

from __future__ import annotations

from textfactor.llm import bpe, chat, decontaminate, hmm, jaccard, linededup, quality, secrets, sharding, vectors

_MODULES = [chat, secrets, sharding, bpe, quality, linededup, hmm, decontaminate, jaccard, vectors]


def queries() -> dict:
    return {name: getattr(m, name) for m in _MODULES for name in dir(m) if name.startswith("op") and name[2].isdigit()}


def oracle_sql() -> dict[str, str]:
    return {k: v for m in _MODULES for k, v in getattr(m, "ORACLE", {}).items()}
