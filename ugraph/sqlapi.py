"""SQL over an entity graph: its tables as views, and ``match_pattern('(x:a)-(y:b)', 0.5)`` as a table in a query."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame

from .operators.engine import Engine, MatchOptions
from .plans.pattern import Pattern

_CALL = re.compile(r"\bmatch_pattern\s*\(\s*'([^']*)'\s*,\s*([0-9.]+(?:[eE]-?\d+)?)\s*(?:,\s*(\d+)\s*)?\)", re.IGNORECASE)


class SqlSession:
    """Queries over one engine. The views are entities, entity_labels, entity_edges, marginals and paths_L (the index's
    paths of L edges), each behind ``prefix``."""

    def __init__(self, engine: Engine, prefix: str = "", options: MatchOptions | None = None):
        self.engine, self.prefix, self.options, self._views = engine, prefix, options, 0
        engine.eg.register(prefix)
        for length, table in engine.idx.paths.items():
            table.createOrReplaceTempView(f"{prefix}paths_{length}")

    def sql(self, text: str) -> DataFrame:
        """Run ``text``. Each call ``match_pattern(pattern, alpha [, L])`` stands for the pattern's matches: a column for
        each node, ple, pn and p. Its plan becomes part of the query's."""
        spark = self.engine.eg.entities.sparkSession

        def view(call: re.Match) -> str:
            o = self.options or MatchOptions()
            if call[3]:
                o = MatchOptions(**{**o.__dict__, "L": int(call[3])})
            self._views += 1
            name = f"{self.prefix}match_{self._views}"
            self.engine.match(Pattern.parse(call[1]), float(call[2]), o).createOrReplaceTempView(name)
            return name

        text = _CALL.sub(view, text)
        if re.search(r"\bmatch_pattern\s*\(", text, re.IGNORECASE):
            raise ValueError("match_pattern takes a quoted pattern, a number and, if wanted, a path length")
        return spark.sql(text)
