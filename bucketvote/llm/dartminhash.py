"""Near-duplicate classes by dart signatures of weighted word shingles.

Darts are thrown, by hashes alone, into the plane of rank and weight above each element; those under an element's
weight hit. Each of `size` coordinates keeps the hit of lowest rank. Two sets agree in a coordinate with the
probability of their weighted Jaccard similarity. Signatures cost a few vector passes over the elements, whatever
their number of coordinates.

Classes are the connected components of texts of similarity 0.8 or more (on sets of five-word shingles of lower-cased
words; a text of fewer words is one shingle). Equal texts are joined by hash first; texts that share a band are paired
with the bucket's most popular members, and each such pair is verified exactly on the whole texts. Buckets that still
hold several classes then compare all close members of different classes exactly, in blocks.

Similarity is of sets: weights other than 1 (`counts`) change signatures and verification alike, for callers who want
similarity of multisets. Nodes of the search are distinct texts, not ids.

Edge cases: null, empty and white texts have no shingle, and each is its own class; rows with a null doc_id are left
out of the search and returned with a null class; repeated rows share a class; texts that share a doc_id are searched
one by one, and a class's id is the least doc_id of its texts; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import NO_ID, id_in, id_out, lean, with_facts, written

SIZE, ROWS, WORDS, THRESHOLD = 128, 4, 5, 0.8
#: Members of a bucket that all its members are compared with.
PIVOTS = 4
#: Members of a bucket in a block, and shingles of their texts; a task compares two blocks at a time.
BLOCK, BLOCK_SHINGLES = 512, 1 << 21
_GOLD, _M1, _M2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_FIRST, _STEP = 2.0**-6, 4.0


def mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(30))
    x = x * _M1
    x ^= x >> np.uint64(27)
    x *= _M2
    x ^= x >> np.uint64(31)
    return x


def _unit(x: np.ndarray) -> np.ndarray:
    return (x >> np.uint64(11)).astype(np.float64) * 2.0**-53


_tails: dict[float, np.ndarray] = {}


def _poisson(mean: float) -> np.ndarray:
    """Cumulative probabilities of counts of darts in an area."""
    if mean not in _tails:
        p, total, out, n = np.exp(-mean), 0.0, [], 0
        while total < 1 - 1e-13 and n < 60 + 4 * mean:
            total += p
            out.append(total)
            n += 1
            p *= mean / n
        _tails[mean] = np.array(out)
    return _tails[mean]


def darts(elements: np.ndarray, weights: np.ndarray, size: int = SIZE, seed: int = 1) -> np.ndarray:
    """Ids of the first dart in each coordinate. Areas are cut alike for all sets: by rank at powers of 4, by weight at powers of 2."""
    out = np.zeros(size, np.uint64)
    free = np.ones(size, bool)
    low, high, level = 0.0, _FIRST, 0
    top = float(weights.max())
    salted = mix(elements + mix(np.array([seed], np.uint64)))
    while free.any():
        ids, ranks = [], []
        under, band = 0.0, 0
        while under < top:
            over = 1.0 if band == 0 else under * 2
            reach = weights > under
            own = salted if reach.all() else salted[reach]
            cell = mix(own + mix(np.array([(level << 8 | band) + 1], np.uint64)))
            n = np.searchsorted(_poisson((over - under) * (high - low)), _unit(cell))
            if n.any():
                which = np.repeat(np.arange(len(n)), n)
                turn = np.arange(len(which)) - np.repeat(np.cumsum(n) - n, n)
                dart = mix(cell[which] + (turn + 1).astype(np.uint64) * _GOLD)
                if band or top < 1 or (weights[reach] < 1).any():
                    hit = under + (over - under) * _unit(mix(dart + _M1)) < weights[reach][which]
                    dart = dart[hit]
                ids.append(dart)
                ranks.append(low + (high - low) * _unit(mix(dart + _M2)))
            under, band = over, band + 1
        if ids:
            dart, rank = np.concatenate(ids), np.concatenate(ranks)
            order = np.argsort(-rank)
            dart = dart[order]
            place = (dart % np.uint64(size)).astype(np.int64)
            first = np.zeros(size, np.uint64)
            got = np.zeros(size, bool)
            first[place], got[place] = dart, True
            new = got & free
            out[new] = first[new]
            free &= ~got
        low, high, level = high, high * _STEP, level + 1
    return out


def bands(signature: np.ndarray, rows: int = ROWS) -> np.ndarray:
    parts = signature.reshape(-1, rows)
    key = np.arange(len(parts), dtype=np.uint64) * _GOLD
    for j in range(rows):
        key = mix(key ^ parts[:, j]) * _M2 + _GOLD
    return key.view(np.int64)


_words: dict[str, int] = {}


def shingles(text: str | None, words: int = WORDS) -> np.ndarray:
    """Hashes of a text's word shingles, in order, repeats kept."""
    found = text.lower().split() if text else []
    if not found:
        return np.zeros(0, np.uint64)
    if len(_words) > 300_000:
        _words.clear()
    known = list(map(_words.get, found))
    if None in known:
        for i, k in enumerate(known):
            if k is None:
                w = found[i]
                known[i] = _words.setdefault(w, xxhash.xxh64_intdigest(w))
    h = np.array(known, np.uint64)
    span = min(words, len(h))
    out = np.zeros(len(h) - span + 1, np.uint64)
    for j in range(span):
        out = (out ^ h[j : len(h) - span + 1 + j]) * _M1 + _GOLD
        out ^= out >> np.uint64(29)
    return out


def weighted(text: str | None, words: int = WORDS, counts: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Elements and their weights: 1 each, or the number of occurrences."""
    elements, n = np.unique(shingles(text, words), return_counts=True)
    return elements, n.astype(np.float64) if counts else np.ones(len(n))


def weighted_jaccard(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray], least: float = 0.0) -> float:
    """Similarity of two weighted sets; 0 if their sums alone show that it is below `least`."""
    x, y = float(a[1].sum()), float(b[1].sum())
    if min(x, y) < least * max(x, y):
        return 0.0
    _, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    low = np.minimum(a[1][i], b[1][j]).sum()
    total = x + y - low
    return float(low / total) if total else 0.0


def signatures(docs: DataFrame, size: int = SIZE, rows: int = ROWS, words: int = WORDS, counts: bool = False) -> DataFrame:
    """A written table (doc_id, text_key, bands, sketch, size), a row per document row; rows without a word or an id have no band."""

    def task(frames):
        import pandas as pd

        for frame in frames:
            out = []
            for doc_id, text, key in zip(frame["doc_id"], frame["text"], frame["text_key"], strict=True):
                elements, weights = weighted(text, words, counts)
                if len(elements) and doc_id != NO_ID:
                    s = darts(elements, weights, size)
                    out.append((doc_id, key, bands(s, rows), (s >> np.uint64(40)).astype(np.uint16).tobytes(), len(elements)))
                else:
                    out.append((doc_id, None, [], b"", 0))
            yield pd.DataFrame(out, columns=["doc_id", "text_key", "bands", "sketch", "size"])

    found = docs.select(id_in("doc_id"), "text", F.md5("text").alias("text_key"))
    return id_out(written(found.mapInPandas(lean(task), "doc_id long, text_key string, bands array<long>, sketch binary, size long"), "signatures"), "doc_id")


def distinct_texts(signed: DataFrame) -> DataFrame:
    """A written table (text_key, head, n, node): the least doc_id of each text, its rows, and an id for the text.

    The id is the head, which one text of each doc_id may carry; further texts of that id get a hash instead.
    """
    firsts = signed.where("text_key is not null").groupBy("text_key").agg(F.min("doc_id").alias("head"), F.count("*").alias("n"))
    firsts = written(firsts, "texts")
    owner = firsts.groupBy("head").agg(F.min("text_key").alias("owner"))
    node = F.when(F.col("text_key") == F.col("owner"), F.col("head")).otherwise(F.xxhash64("text_key", "head"))
    return written(firsts.join(owner, "head").select("text_key", "head", "n", node.alias("node")), "nodes")


def shared_bands(heads: DataFrame) -> DataFrame:
    """A written table (key, band, node, n, mass) of the members of buckets of n > 1; mass counts the shingles of all members."""
    rows = heads.select("node", "size", F.posexplode("bands").alias("band", "key"))
    sums = rows.groupBy("key").agg(F.count("*").alias("n"), F.sum("size").alias("mass")).where("n > 1")
    return written(rows.drop("size").join(sums, "key"), "buckets")


def candidate_pairs(shared: DataFrame, pivots: int = PIVOTS) -> DataFrame:
    """Pairs (a, b) of nodes that share a band, b among the bucket's `pivots` most popular members.

    A text is popular if its buckets are large: then it lies in the middle of a family of copies. The limit by
    rank runs before the shuffle (a window group limit), so a huge bucket sends a few rows a task.
    """
    popular = shared.groupBy("node").agg(F.sum("n").alias("popularity"))
    ranked = shared.join(popular, "node").withColumn("place", F.row_number().over(Window.partitionBy("key").orderBy(F.desc("popularity"), "node")))
    chosen = ranked.where(F.col("place") <= pivots).select("key", F.col("node").alias("b"))
    both = shared.select("key", F.col("node").alias("a")).join(chosen, "key").where("a <> b")
    return both.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def close_across(sketch: np.ndarray, kinds: np.ndarray, x: int, right: np.ndarray, band: int, least: float, rows: int) -> np.ndarray:
    """Members of `right` of another class than x whose signatures agree in a share of `least` and share no band before this one."""
    other = right[kinds[right] != kinds[x]]
    if not len(other):
        return other
    same = sketch[other] == sketch[x]
    near = same.mean(axis=1) >= least
    other, same = other[near], same[near]
    return other[same.reshape(len(other), -1, rows).all(axis=2).argmax(axis=1) == band] if len(other) else other


def links_across(shared: DataFrame, heads: DataFrame, docs: DataFrame, classes: DataFrame, threshold: float, words: int, counts: bool, pivots: int = PIVOTS, rows: int = ROWS, slack: float = 0.2, block: int = BLOCK) -> DataFrame:
    """Links (a, b) of members of one bucket and different classes, enough of them to join all classes that hang together there.

    In a bucket of pivots + 1 members every pair has a pivot. Larger ones that hold several classes are cut into blocks by
    a hash of the node, and every two blocks meet in a group of their own: no group grows with the bucket. A group first
    finds by signatures the members with a close one of another class, in the first band that the two share; only those
    members' texts are sent to the group, which compares all their close pairs exactly and returns a link for each two
    classes that it joins. Pairs are made inside a task and never become rows.
    """
    part = shared.where(F.col("n") > pivots + 1).join(classes, "node", "left").withColumn("class", F.coalesce("class", "node"))
    split = part.groupBy("key").agg(F.min("class").alias("lo"), F.max("class").alias("hi")).where("lo <> hi").select("key")
    blocks = F.ceil(F.greatest(F.col("n") / block, F.col("mass") / BLOCK_SHINGLES))
    placed = part.join(split, "key").withColumn("i", F.pmod(F.xxhash64(F.lit(17), "node"), blocks)).withColumn("j", F.explode(F.sequence(F.lit(0).cast("long"), blocks - 1)))
    sides = placed.select("key", F.least("i", "j").alias("u"), F.greatest("i", "j").alias("v"), "band", "i", "node", "class").join(heads.select("node", "sketch"), "node")

    def pairs_of(frame):
        kinds, place, band, u = frame["class"].to_numpy(), frame["i"].to_numpy(), int(frame["band"].iloc[0]), frame["u"].iloc[0]
        sketch = np.stack([np.frombuffer(x, np.uint16) for x in frame["sketch"]])
        left, right = np.flatnonzero(place == u), np.flatnonzero(place == frame["v"].iloc[0])
        for x in left:
            yield x, close_across(sketch, kinds, x, right, band, threshold - slack, rows)

    def active(frame):
        took = np.zeros(len(frame), bool)
        for x, other in pairs_of(frame):
            took[other] = True
            took[x] |= len(other) > 0
        return frame[took]

    def join(frame):
        import pandas as pd

        frame = frame.sort_values("node", kind="stable").reset_index(drop=True)
        ids, kinds, texts = frame["node"].tolist(), frame["class"].tolist(), frame["text"].tolist()
        root = {k: k for k in kinds}
        sets: dict[int, tuple] = {}

        def find(k):
            while root[k] != k:
                root[k] = k = root[root[k]]
            return k

        def elements(i):
            if i not in sets:
                sets[i] = weighted(texts[i], words, counts)
            return sets[i]

        out = []
        for x, other in pairs_of(frame):
            for y in other.tolist():
                p, q = find(kinds[x]), find(kinds[y])
                if p != q and weighted_jaccard(elements(x), elements(y), threshold) >= threshold:
                    root[max(p, q)] = min(p, q)
                    out.append((min(ids[x], ids[y]), max(ids[x], ids[y])))
        return pd.DataFrame(out, columns=["a", "b"], dtype="int64")

    some = written(sides.groupBy("key", "u", "v").applyInPandas(active, sides.schema), "active-members")
    texts = texts_of(some.select("node").distinct(), heads, docs)
    return written(some.join(texts, "node").groupBy("key", "u", "v").applyInPandas(join, "a long, b long").distinct(), "links-across")


def maybe_among(docs: DataFrame, ids: DataFrame, bits: int = 1 << 24) -> DataFrame:
    """docs (doc_id, text) whose id may be among ids, by a bitmap of hashed ids: most other texts are not shuffled.

    The bitmap has bits / 64 rows at most, whatever the number of ids, so it may be broadcast; when it fills up, more pass.
    """

    def slot(c: str):
        return F.pmod(F.xxhash64(F.lit(11), c), F.lit(bits))

    words = ids.select(slot("doc_id").alias("h")).groupBy(F.floor(F.col("h") / 64).alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, cast(h % 64 as int))")).alias("m"))
    hit = (F.floor(F.col("_h") / 64) == F.col("w")) & (F.expr("shiftrightunsigned(m, cast(_h % 64 as int)) & 1") == 1)
    return docs.withColumn("_h", slot("doc_id")).join(F.broadcast(words), hit, "left_semi").drop("_h")


def texts_of(nodes: DataFrame, heads: DataFrame, docs: DataFrame) -> DataFrame:
    """A written table (node, text)."""
    needed = nodes.join(heads.select("node", "doc_id", "text_key"), "node")
    some = maybe_among(docs.where("doc_id is not null and text is not null").select("doc_id", "text"), needed).withColumn("text_key", F.md5("text"))
    return written(some.join(needed, ["doc_id", "text_key"]).dropDuplicates(["node"]).select("node", "text"), "pair-texts")


def verified(pairs: DataFrame, heads: DataFrame, docs: DataFrame, threshold: float, words: int = WORDS, counts: bool = False, slack: float = 0.2) -> DataFrame:
    """Pairs whose similarity on the whole texts reaches the threshold; those whose signatures differ far too much are not read."""

    def near(frames):
        for frame in frames:
            same = [float((np.frombuffer(x, np.uint16) == np.frombuffer(y, np.uint16)).mean()) for x, y in zip(frame["x"], frame["y"], strict=True)]
            yield frame.loc[np.array(same, float) >= threshold - slack, ["a", "b"]]

    def exact(frames):
        known: tuple[str, tuple] | None = None
        for frame in frames:
            keep = []
            for x, y in zip(frame["x"], frame["y"], strict=True):
                if known is None or known[0] != x:
                    known = (x, weighted(x, words, counts))
                keep.append(weighted_jaccard(known[1], weighted(y, words, counts)) >= threshold)
            yield frame.loc[np.array(keep, bool), ["a", "b"]]

    def beside(p: DataFrame, values: DataFrame, value: str) -> DataFrame:
        one = p.join(values.select(F.col("node").alias("b"), F.col(value).alias("y")), "b")
        return one.join(values.select(F.col("node").alias("a"), F.col(value).alias("x")), "a")

    close = written(beside(pairs, heads, "sketch").select("a", "b", "x", "y").mapInPandas(lean(near), "a long, b long"), "close-pairs")
    texts = texts_of(close.select("a").union(close.select("b")).distinct().withColumnRenamed("a", "node"), heads, docs)
    return written(beside(close, texts, "text").select("a", "b", "x", "y").mapInPandas(lean(exact), "a long, b long"), "links")


def components(links: DataFrame) -> DataFrame:
    """(node, class) of linked nodes, class the smallest node: large-star and small-star rounds until nothing moves."""

    def stars(edges: DataFrame, small: bool) -> DataFrame:
        both = edges if small else edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("b" if small else "a").agg(F.min("a" if small else "b").alias("m"))
        if small:  # edges are (lower a, upper b): tie every lower neighbour of b, and b, to the lowest
            out = edges.join(low, "b")
            made = out.select(F.col("m").alias("a"), F.col("a").alias("b")).union(out.select(F.col("m").alias("a"), "b"))
        else:
            out = both.join(low.withColumn("m", F.least("a", "m")), "a").where("b > a")
            made = out.select(F.col("m").alias("a"), "b")
        return made.where("a < b").distinct()

    def state(edges: DataFrame):
        r = edges.agg(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h")).first()
        return r["n"], r["h"]

    edges = written(links.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a < b").distinct(), "edges")
    now = state(edges)
    while True:
        edges = written(stars(stars(edges, False), True), "edges")
        before, now = now, state(edges)
        if now == before:
            break
    return edges.groupBy("b").agg(F.min("a").alias("class")).withColumnRenamed("b", "node")


def text_classes(docs: DataFrame, threshold: float = THRESHOLD, size: int = SIZE, rows: int = ROWS, words: int = WORDS, counts: bool = False, pivots: int = PIVOTS) -> tuple[DataFrame, DataFrame]:
    """The signed rows, and (text_key, n, class_id, first_key) of the texts that share a class with another row.

    class_id is the least doc_id of the class, first_key the least text_key of that document in it.
    """
    signed = signatures(docs, size, rows, words, counts)
    nodes = distinct_texts(signed)
    own = nodes.select(F.col("head").alias("doc_id"), "text_key", "node")
    heads = written(signed.join(own, ["doc_id", "text_key"]).dropDuplicates(["node"]), "head-signatures")
    shared = shared_bands(heads)
    links = verified(candidate_pairs(shared, pivots), heads, docs, threshold, words, counts)
    parts = written(components(links), "parts")
    more = links_across(shared, heads, docs, parts, threshold, words, counts, pivots, rows)
    # what is joined already is a star; the new links join stars
    upper = parts if more.isEmpty() else components(parts.select(F.col("class").alias("a"), F.col("node").alias("b")).unionByName(more))
    # a class's root is its own node, which no link's upper end names
    upper = upper.unionByName(upper.select(F.col("class").alias("node"), "class").distinct())
    linked = written(upper.join(nodes, "node"), "linked-texts")
    least = linked.groupBy("class").agg(F.min(F.struct("head", "text_key")).alias("least")).select("class", F.col("least.head").alias("class_id"), F.col("least.text_key").alias("first_key"))
    near = linked.join(least, "class").select("text_key", "n", "class_id", "first_key")
    alone = nodes.where("n > 1").join(linked.select("node"), "node", "left_anti").select("text_key", "n", F.col("head").alias("class_id"), F.col("text_key").alias("first_key"))
    return signed, written(near.unionByName(alone), "text-classes")


def near_duplicate_classes(docs: DataFrame, **options) -> DataFrame:
    """A row per document row: doc_id, class_id (the smallest doc_id of its class)."""
    signed, classes = text_classes(docs, **options)
    rows = with_facts(signed.select("doc_id", "text_key"), classes, "text_key")
    return rows.select("doc_id", F.coalesce("class_id", "doc_id").alias("class_id"))


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """One row of each class, of the lowest doc_id, in docs' columns whatever their names; rows without a word or an id stay."""
    signed, classes = text_classes(docs, **options)
    rows = with_facts(signed.where("text_key is not null").select("doc_id", "text_key"), classes, "text_key").where("class_id is not null")
    # (document, text) pairs to decide on: all rows go but those of the class's first, and of its repeats one stays
    told = rows.groupBy("doc_id", "text_key").agg(F.first((F.col("doc_id") == F.col("class_id")) & (F.col("text_key") == F.col("first_key"))).alias("stays"), F.count("*").alias("times"))
    row = F.struct(*docs.columns)
    keyed = docs.select(row.alias("row"), F.col("doc_id").alias("doc_id"), F.md5("text").alias("text_key"))
    joined = keyed.join(told.where("times > 1 or not stays"), ["doc_id", "text_key"], "left").where("stays is null or stays")
    once, repeated = joined.where("stays is null").select("row"), joined.where("stays")
    # json holds rows of any type, in a fixed order of columns: repeats that differ elsewhere keep the least
    return once.unionByName(repeated.groupBy("doc_id", "text_key").agg(F.min_by("row", F.to_json("row")).alias("row")).select("row")).select("row.*")
