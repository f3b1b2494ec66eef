"""Table functions for SQL users."""

from __future__ import annotations

import re
from hashlib import md5

from pyspark.sql.functions import udtf

from .hashing import PRIME, coins, hash_coefficients


@udtf(returnType="table_id: int, bucket_key: string")
class lsh_keys:
    """lsh_keys(text, k, tables): a row per table with the text's key; none for a text without words. The same keys as `hashing.keys_of`."""

    def eval(self, text: str, k: int, tables: int):
        words = set(re.sub("[^a-z0-9]+", " ", (text or "").lower()).split())
        if not words:
            return
        bins, (a, b) = k * tables, hash_coefficients(1, 1)[0]
        least: dict[int, int] = {}
        for w in words:
            u = (int(md5(w.encode()).hexdigest()[:7], 16) * a + b) % PRIME
            at = u * bins // PRIME
            least[at] = min(u, least.get(at, u))
        toss, filled = coins(bins, 1), []
        for i in range(bins):
            step = 1 if toss[i] else -1
            filled.append(least[next(j for n in range(bins) if (j := (i + step * n) % bins) in least)])
        for t in range(tables):
            yield t, "-".join(map(str, filled[t * k : t * k + k]))


@udtf(returnType="query_id: long, rank: int, id: long, upper: long, votes: long")
class sketch_top:
    """sketch_top(TABLE(cells) PARTITION BY (query_id), k, depth, width): the best ids of each query's merged cells, at most depth x width a partition."""

    def __init__(self):
        self.held, self.settings, self.key = {}, None, None

    def eval(self, cell, k: int, depth: int, width: int):
        self.key, self.settings = cell["query_id"], (k, depth, width)
        self.held[cell["row"], cell["col"]] = cell["total"], cell["cand"], cell["votes"]

    def terminate(self):
        from ..operators.counters import top_of

        for n, (ident, upper, votes) in enumerate(top_of(self.held, *self.settings) if self.settings else []):
            yield self.key, n + 1, ident, upper, votes
