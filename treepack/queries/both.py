"""Registers a query whose Spark SQL and oracle SQL differ at most in a few words."""

from __future__ import annotations

import re

from treepack.registry import query
from treepack.sources.tables import load

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def both(name: str, section: str, text: str, spark: str | None = None) -> None:
    """text uses table names in braces; spark replaces it on the Spark side where dialects differ."""
    oracle = re.sub(r"\{(\w+)\}", r"\1", text)
    source = spark or text

    def run(session, d):
        used = {t: load(session, d, t) for t in TABLES if "{" + t + "}" in source}
        return session.sql(source, **used)

    query(name, section, oracle)(run)
