"""DuckDB SQL of the queries, built from common table expressions in long form, apart from the engine's array forms."""

from __future__ import annotations

from .functions.hashing import OFFSET, PRIME, coins, hash_coefficients
from .operators.sketch import SEED as SKETCH_SEED


def num(x: str) -> str:
    return f"CAST('0x' || substr(md5(CAST({x} AS VARCHAR)), 1, 7) AS BIGINT)"


def uni(x: str, a: int, b: int) -> str:
    return f"(({x}) * {a} + {b}) % {PRIME}"


WORDS = "(SELECT {id} id, unnest(string_split(trim(regexp_replace(lower({text}), '[^a-z0-9]+', ' ', 'g')), ' ')) token, generate_subscripts(string_split(trim(regexp_replace(lower({text}), '[^a-z0-9]+', ' ', 'g')), ' '), 1) pos FROM {table})"


def words(table: str = "documents", ident: str = "doc_id", text: str = "text") -> str:
    return WORDS.format(table=table, id=ident, text=text)


def sets(table: str = "documents", ident: str = "doc_id", text: str = "text") -> str:
    return f"SELECT DISTINCT id, token FROM {words(table, ident, text)} WHERE token <> ''"


LINE_SETS = """SELECT DISTINCT CAST('0x' || substr(md5(concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber, strftime(l_shipdate, '%Y-%m-%d'), CAST(round(l_extendedprice * 100) AS BIGINT))), 1, 14) AS BIGINT) id,
 unnest(['partkey=' || l_partkey, 'suppkey=' || l_suppkey, 'returnflag=' || l_returnflag, 'linestatus=' || l_linestatus, 'quantity=' || CAST(round(l_quantity) AS BIGINT), 'discount=' || CAST(round(l_discount * 100) AS BIGINT), 'tax=' || CAST(round(l_tax * 100) AS BIGINT), 'month=' || strftime(l_shipdate, '%Y-%m')]) token FROM lineitem"""


class Build:
    """Common table expressions, one after another."""

    def __init__(self, set_sql: str | None = None):
        self.parts = [f"sets AS ({set_sql or sets()})"]

    def add(self, name: str, sql: str) -> Build:
        self.parts.append(f"{name} AS ({sql})")
        return self

    def select(self, sql: str) -> str:
        return f"WITH RECURSIVE {', '.join(self.parts)} {sql}"

    def signature(self, bins: int, seed: int = 1) -> Build:
        a, b = hash_coefficients(seed, 1)[0]
        self.add("hashed", f"SELECT id, {uni(num('token'), a, b)} u FROM sets")
        return self.add("sig", f"SELECT id, CAST(u * {bins} // {PRIME} AS INTEGER) bin, min(u) AS value FROM hashed GROUP BY ALL")

    def dense(self, bins: int, seed: int = 1, coin: str = "per_bin", offset: bool = False) -> Build:
        toss = ", ".join(f"({i}, {c})" for i, c in enumerate(coins(bins, seed)))
        pick = {"per_bin": "coin = 1", "always_right": "true", "closest_side": "rd < ld OR (rd = ld AND coin = 1)"}[coin]
        far = f" + {OFFSET} * " if offset else " + 0 * "
        self.add("toss", f"SELECT * FROM (VALUES {toss}) t(bin, coin)")
        right, left = f"(f.bin - t.bin + {bins}) % {bins}", f"(t.bin - f.bin + {bins}) % {bins}"
        self.add("near", f"SELECT f.id, t.bin, t.coin, min({right}) rd, arg_min(f.value, {right}) rv, min({left}) ld, arg_min(f.value, {left}) lv FROM sig f, toss t GROUP BY ALL")
        return self.add("full_sig", f"SELECT id, bin, CASE WHEN rd = 0 THEN rv WHEN {pick} THEN rv{far}rd ELSE lv{far}ld END AS value FROM near")

    def minhash(self, bins: int, seed: int = 1) -> Build:
        co = hash_coefficients(seed, bins)
        return self.add("full_sig", " UNION ALL ".join(f"SELECT id, CAST({i} AS INTEGER) bin, min({uni(num('token'), a, b)}) AS value FROM sets GROUP BY id" for i, (a, b) in enumerate(co)))

    def keys(self, k: int, tables: int, layout: str = "block") -> Build:
        table = f"bin // {k}" if layout == "block" else f"bin % {tables}"
        return self.add("keys", f"SELECT id, CAST({table} AS INTEGER) table_id, string_agg(CAST(value AS VARCHAR), '-' ORDER BY bin) bucket_key FROM full_sig GROUP BY ALL")

    def buckets(self, k: int, tables: int, nodes: int, **options) -> Build:
        layout = options.pop("layout", "block")
        if options.pop("family", "") == "minhash":
            self.minhash(k * tables).keys(k, tables, layout)
        else:
            self.signature(k * tables).dense(k * tables, **options).keys(k, tables, layout)
        return self.add("buckets", f"SELECT CAST({num('id')} % {nodes} AS INTEGER) node, table_id, bucket_key, id FROM keys")

    def asked(self, n: int | None = None) -> Build:
        """Query rows: ids divisible by 100, or the n of least hash."""
        which = "WHERE id % 100 = 0" if n is None else f"ORDER BY {num('id')}, id LIMIT {n}"
        return self.add("asked", f"SELECT id query_id FROM (SELECT DISTINCT id FROM sets) {which}")

    def queries(self, n: int | None = None) -> Build:
        self.asked(n)
        return self.add("qkeys", "SELECT id query_id, table_id, bucket_key FROM keys WHERE id IN (SELECT query_id FROM asked)")

    def spread(self, src: str, depth: int, width: int) -> str:
        return " UNION ALL ".join(f"SELECT *, {r} AS \"row\", CAST({uni(num('id'), *hash_coefficients(SKETCH_SEED, r + 1)[r])} % {width} AS INTEGER) col FROM {src}" for r in range(depth))

    def cells(self, depth: int, width: int, src: str = "buckets", name: str = "cells") -> Build:
        self.add(f"spread_{name}", self.spread(src, depth, width))
        salt = num("concat_ws('/', id, \"row\", table_id)")
        return self.add(name, f'SELECT node, table_id, bucket_key, "row", col, CAST(count(*) AS BIGINT) total, min({{s: {salt}, c: id}}).c cand, CAST(CASE WHEN count(*) = 1 THEN 1 ELSE 0 END AS BIGINT) votes FROM spread_{name} GROUP BY ALL')

    def merge(self, name: str, src: str, keys: str) -> Build:
        salt = num("concat_ws('/', cand, \"row\")")
        self.add(f"{name}_v", f'SELECT {keys}, "row", col, cand, sum(total) t, sum(votes) v, {salt} s FROM {src} GROUP BY ALL')
        self.add(f"{name}_r", f'SELECT *, row_number() OVER w n, lead(v) OVER w nx, sum(t) OVER (PARTITION BY {keys}, "row", col) tt FROM {name}_v WINDOW w AS (PARTITION BY {keys}, "row", col ORDER BY v DESC, s, cand)')
        return self.add(name, f'SELECT {keys}, "row", col, CAST(tt AS BIGINT) total, cand, CAST(v - coalesce(nx, 0) AS BIGINT) votes FROM {name}_r WHERE n = 1')

    def local(self) -> Build:
        self.add("probed", "SELECT q.query_id, c.* FROM qkeys q JOIN cells c USING (table_id, bucket_key)")
        return self.merge("local_cells", "probed", "query_id, node")

    def tree(self, nodes: int) -> Build:
        src, left, i = "local_cells", nodes, 0
        while left > 1:
            self.add(f"up{i}", f"SELECT query_id, node // 2 node, \"row\", col, total, cand, votes FROM {src}")
            self.merge(f"round{i}", f"up{i}", "query_id, node")
            src, left, i = f"round{i}", -(-left // 2), i + 1
        return self.add("merged", f"SELECT * FROM {src}")

    def linear(self, nodes: int) -> Build:
        self.add("step0", "SELECT * EXCLUDE (node) FROM local_cells WHERE node = 0")
        for i in range(1, nodes):
            self.add(f"in{i}", f"SELECT * FROM step{i - 1} UNION ALL SELECT * EXCLUDE (node) FROM local_cells WHERE node = {i}")
            self.merge(f"step{i}", f"in{i}", "query_id")
        return self.add("merged", f"SELECT * FROM step{nodes - 1}")

    def top(self, k: int, depth: int, width: int, exclude_self: bool = True) -> Build:
        self.add("cand_ids", "SELECT DISTINCT query_id, cand AS id FROM merged")
        self.add("cand_rows", self.spread("cand_ids", depth, width))
        self.add("bounds", 'SELECT r.query_id, r.id, min(coalesce(m.total, 0)) AS upper, max(CASE WHEN m.cand = r.id THEN m.votes ELSE 0 END) votes FROM cand_rows r LEFT JOIN merged m ON m.query_id = r.query_id AND m."row" = r."row" AND m.col = r.col GROUP BY ALL')
        self.add("placed", f"SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY votes DESC, upper DESC, id) n FROM bounds QUALIFY n <= {k + exclude_self}")
        where = "WHERE query_id <> id" if exclude_self else ""
        return self.add("answers", f'SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY n) AS INTEGER) AS "rank", id, CAST(upper AS BIGINT) AS upper, CAST(votes AS BIGINT) votes FROM placed {where} QUALIFY "rank" <= {k}')

    def counts(self, src: str = "buckets") -> Build:
        return self.add("counts", f"SELECT q.query_id, b.id, CAST(count(*) AS BIGINT) hits FROM qkeys q JOIN {src} b USING (table_id, bucket_key) GROUP BY ALL")

    def pairs(self, where: str = "a.id <> b.id") -> Build:
        self.add("sizes", "SELECT id, count(*) n FROM sets GROUP BY id")
        return self.add("sim_rows", f"SELECT a.id query_id, b.id, count(*) AS shared, any_value(sa.n) na, any_value(sb.n) nb FROM sets a JOIN sets b ON a.token = b.token AND {where} JOIN sizes sa ON sa.id = a.id JOIN sizes sb ON sb.id = b.id WHERE a.id IN (SELECT query_id FROM asked) GROUP BY ALL")

    def agreement(self) -> Build:
        """Pairs of sim_rows with the share of bins in which their full_sig values agree."""
        self.add("bins", "SELECT count(DISTINCT bin) b FROM full_sig")
        self.add("same", "SELECT s.query_id, s.id, count(*) c FROM sim_rows s JOIN full_sig x ON x.id = s.query_id JOIN full_sig y ON y.id = s.id AND y.bin = x.bin AND y.value = x.value GROUP BY ALL")
        return self.add("agreed", "SELECT s.*, coalesce(c, 0) / CAST(b AS DOUBLE) rate FROM sim_rows s LEFT JOIN same m ON m.query_id = s.query_id AND m.id = s.id, bins")

    def hits(self, k: int, src: str = "counts", name: str = "placed_ids") -> Build:
        return self.add(name, f"SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY hits DESC, id) AS rk, id FROM {src} WHERE query_id <> id QUALIFY rk <= {k}")

    def graded(self, src: str = "placed_ids", ks: tuple[int, ...] = (10,), name: str = "graded") -> Build:
        """(k, s_at_k, coverage, queries) of placed answers (query_id, rk, id) by exact cosine; missing answers are left out of the mean."""
        self.add(f"{name}_c", f"SELECT p.query_id, p.rk, p.id, count(a.token) na, count(b.token) both_n FROM {src} p JOIN sets a ON a.id = p.query_id LEFT JOIN sets b ON b.id = p.id AND b.token = a.token GROUP BY ALL")
        self.add(f"{name}_s", f"SELECT c.*, both_n / sqrt(CAST(na * n AS DOUBLE)) sim FROM {name}_c c JOIN (SELECT id, count(*) n FROM sets GROUP BY id) z ON z.id = c.id")
        wanted = ", ".join(f"({k})" for k in ks)
        per = f"SELECT k, query_id, sum(sim) s, count(*) n FROM {name}_s, (VALUES {wanted}) t(k) WHERE rk <= k GROUP BY ALL"
        n = "(SELECT count(*) FROM asked)"
        return self.add(name, f"SELECT CAST(k AS INTEGER) k, round(avg(s / n), 6) s_at_k, round(sum(n) / CAST(k * {n} AS DOUBLE), 6) coverage, CAST({n} AS BIGINT) queries FROM ({per}) GROUP BY k")


def union_all(parts: list[str]) -> str:
    return " UNION ALL ".join(f"SELECT * FROM ({p})" for p in parts)
