"""Queries of this subpackage and their SQL, by name."""

from __future__ import annotations

import importlib

#: Query name -> module that defines it; a module may define ORACLE_SQL.
MODULES = {
    "op1_subword_quality": "subword_quality",
    "op2_ppm_language": "ppm_language",
    "op3_chat_parts": "chat_parts",
    "op4_isolation_rules": "isolation_rules",
    "op5_warc_index": "warc_index",
    "op6_simhash_bktree": "simhash_bktree",
    "op7_line_dedup": "line_dedup",
    "op8_splitter_shards": "splitter_shards",
    "op9_bpe": "bpe_automaton",
    "op10_decontaminate": "decontaminate",
}


def _module(name: str):
    return importlib.import_module(f"{__package__}.{MODULES[name]}")


def _lazy(name: str):
    """The query; its module is imported when the query is built."""

    def run(spark, sf_dir):
        return getattr(_module(name), name)(spark, sf_dir)

    run.__name__ = name
    return run


def queries() -> dict:
    return {name: _lazy(name) for name in MODULES}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name in MODULES if (sql := getattr(_module(name), "ORACLE_SQL", None))}
