"""Exact n-gram Jaccard join with a token-group matrix.

Tokens are 64-bit hashes of word shingles. The steps:

1. One pass makes of every text its set of tokens and keeps a digest of the set, its size and a few minima
   under different permutations. Equal sets become one node (the smallest id).
2. *Groups of similar documents.* Nodes that share a key of two minima are tried against the smallest node that
   has it, and verified; those still unconnected are tried against three others. Verified links make the
   groups: one group holds nodes known to be connected, of one size band.
3. *Token-group matrix.* All tokens have one global order, in which common ones come last (by a sketch of fixed
   size) and ties go by hash. Two sets that link share tokens among the first quarter of both. So a group's row
   holds the union of its members' first quarters, one entry a token however many members have it.
4. *Bound and open.* Two groups can only hold a link if they share enough entries: a link of sizes n and m has
   ceil(75 (n + m) / 175) common tokens, of which those behind the first quarter of the one that ends first
   can be at most ceil(3n/4) - 1. Only group pairs that reach the bound are opened: their members are paired
   and verified on whole texts. Pairs inside one group are never needed, as they're connected already.
5. Components of all links.

No cap, no sample: the sketch only chooses the order, and any order is right. Texts are fetched for verified
pairs only, through an id filter of fixed size.

Defined results: words are runs of anything but the six ASCII blanks, with A-Z lower-cased. A text of fewer
than ``width`` words is one shingle; a null text or one without words has an empty set and no link. A row with
a null id gets its set size and a null component. Repeated ids with different texts: each text is a node of
its own under that id; their component is the smallest id reachable. Extra columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import rows_with, rows_without, sliced, written
from .components import components

WIDTH = 5
PERCENT = 75
MINIMA = 6
#: Which members of those with a common key the others are tried against, round by round: (order, the first?).
LEADS = ((("node", True),), (("node", False), ("hash", True), ("hash", False)))
SKETCH_BITS = 18
#: Buckets that one task reports to the sketch; it only steers the order.
SKETCH_ROWS = 4096
BAND = 1.05
#: Words, or sets, that a task keeps in mind; forgetting them costs time only.
MOST_KEPT = 150_000
#: Members of a large group that are opened together.
BLOCK = 32
_STEPS = tuple(np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3, 0x589965CC75374CC3))
_MINUS_ONE = np.uint64(0xFFFFFFFFFFFFFFFF)


class WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) > MOST_KEPT:
            self.clear()
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


def shingle_set(text: str | None, hashes: WordHashes, width: int = WIDTH) -> np.ndarray:
    """The sorted distinct 64-bit tokens of a text."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    n = len(words)
    if not n:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(hashes.__getitem__, words), np.uint64, n)
    k = min(width, n)
    s = h[: n - k + 1] + np.uint64(k)
    for j in range(1, k):
        s = (s ^ (s >> np.uint64(29))) * _STEPS[0] + h[j : n - k + 1 + j]
    s = (s ^ (s >> np.uint64(32))) * _STEPS[1]
    s ^= s >> np.uint64(29)
    s.sort()
    return s[np.append(True, s[1:] != s[:-1])]


def links_exactly(a: np.ndarray, b: np.ndarray, percent: int = PERCENT) -> bool:
    if not len(a) or not len(b) or 100 * min(len(a), len(b)) < percent * max(len(a), len(b)):
        return False
    both = np.concatenate((a, b))
    both.sort()
    shared = int(np.count_nonzero(both[1:] == both[:-1]))
    return 100 * shared >= percent * (len(a) + len(b) - shared)


def _digest(tokens: np.ndarray) -> int:
    return xxhash.xxh3_64_intdigest(tokens.tobytes()) - (1 << 63)


def _minima(tokens: np.ndarray, i: int) -> int:
    """A key of two minima, under two permutations of the tokens."""
    p, q = tokens * _STEPS[i + 2], tokens * (_STEPS[i + 2] ^ _STEPS[0] << np.uint64(1))
    p, q = int((p ^ (p >> np.uint64(31))).min()), int((q ^ (q >> np.uint64(30))).min())
    return ((p * 0x9E3779B97F4A7C15 + q) & 0xFFFFFFFFFFFFFFFF) - (1 << 63)


def _signatures(docs: DataFrame, width: int) -> DataFrame:
    """kind 0: a document (id, sid, n, m0...). kind 1: a bucket of the sketch (id: the bucket, n: its excess)."""

    def run(batches):
        hashes, counts, sets = WordHashes(), np.zeros(1 << SKETCH_BITS, np.int64), 0
        for batch in sliced(batches):
            rows = {k: [] for k in ("id", "sid", "n", *(f"m{i}" for i in range(MINIMA)))}
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                s = shingle_set(text, hashes, width)
                rows["id"].append(doc)
                rows["n"].append(len(s))
                rows["sid"].append(_digest(s) if len(s) else None)
                if len(s):
                    counts += np.bincount((s >> np.uint64(64 - SKETCH_BITS)).astype(np.int64), minlength=len(counts)) if len(s) > 50_000 else 0
                    if len(s) <= 50_000:
                        np.add.at(counts, (s >> np.uint64(64 - SKETCH_BITS)).astype(np.int64), 1)
                    sets += len(s)
                for i in range(MINIMA):
                    if len(s):
                        rows[f"m{i}"].append(_minima(s, i))
                    else:
                        rows[f"m{i}"].append(None)
            yield pa.RecordBatch.from_pydict({"kind": pa.array([0] * len(rows["id"]), pa.int8())} | {k: pa.array(v, pa.int64()) for k, v in rows.items()})
        mean = sets / len(counts)
        over = counts - int(mean + 4 * mean**0.5 + 4)
        top = np.flatnonzero(over > 0)
        top = top[np.argsort(-over[top], kind="stable")[:SKETCH_ROWS]]
        none = pa.nulls(len(top), pa.int64())
        yield pa.RecordBatch.from_pydict({"kind": pa.array([1] * len(top), pa.int8()), "id": pa.array(top, pa.int64()), "sid": none, "n": pa.array(over[top], pa.int64())} | {f"m{i}": none for i in range(MINIMA)})

    return docs.mapInArrow(run, "kind byte, id long, sid long, n long, " + ", ".join(f"m{i} long" for i in range(MINIMA)))


def _prefixes(docs: DataFrame, levels: np.ndarray, width: int, percent: int) -> DataFrame:
    """(sid, n, toks): the first tokens of every set in the global order, once a task for sets that repeat."""
    shared = docs.sparkSession.sparkContext.broadcast(levels)  # 2**SKETCH_BITS bytes

    def run(batches):
        hashes, level, seen = WordHashes(), shared.value, set()
        for batch in sliced(batches):
            sids, ns, toks = [], [], []
            for text in batch.column(1).to_pylist():
                s = shingle_set(text, hashes, width)
                n = len(s)
                if not n or (key := (_digest(s), n)) in seen:
                    continue
                if len(seen) > MOST_KEPT:
                    seen.clear()
                seen.add(key)
                p = n - -(-percent * n // 100) + 1
                order = np.argsort(level[(s >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)], kind="stable")[:p]
                sids.append(key[0])
                ns.append(n)
                toks.append(s[order].view(np.int64))
            lens = np.fromiter(map(len, toks), np.int64, len(toks))
            flat = pa.array(np.concatenate(toks) if toks else np.empty(0, np.int64), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(sids, pa.int64()), pa.array(ns, pa.int64()), pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(lens)), pa.int32()), flat)], ["sid", "n", "toks"])

    return docs.mapInArrow(run, "sid long, n long, toks array<long>")


def _entries(rows: DataFrame) -> DataFrame:
    """(root, n, toks) to (token, root, span): one entry a token and group in each batch; span is least size, most size."""

    def run(batches):
        for batch in sliced(batches):
            lists = batch.column(2)
            lens = np.diff(lists.offsets.to_numpy())
            token = lists.flatten().to_numpy(zero_copy_only=False)
            n = np.repeat(batch.column(1).to_numpy(zero_copy_only=False), lens)
            root = np.repeat(batch.column(0).to_numpy(zero_copy_only=False), lens)
            band = (np.log(np.maximum(n, 1)) / np.log(BAND) + 1e-9).astype(np.int32)
            order = np.lexsort((n, band, root, token))
            token, root, band, n = token[order], root[order], band[order], n[order]
            first = np.append(True, (token[1:] != token[:-1]) | (root[1:] != root[:-1]) | (band[1:] != band[:-1]))[: len(token)]
            last = np.append(first[1:], True)[: len(token)]
            yield pa.RecordBatch.from_arrays([pa.array(token[first]), pa.array(root[first]), pa.array(n[first] << 32 | n[last])], ["token", "root", "span"])

    return rows.select("root", "n", "toks").mapInArrow(run, "token long, root long, span long")


def _verified(docs: DataFrame, pairs: DataFrame, width: int, percent: int) -> DataFrame:
    """Those of pairs (a, b) of ids whose texts link. ``b`` should be the end that repeats."""
    ends = written(pairs.distinct(), "pairs")
    text = lambda side: rows_with(docs.select(F.col("_id").alias(side), F.col("_text").alias(f"t{side}")), ends.select(side), side).hint("merge")
    rows = ends.join(text("a"), "a").join(text("b"), "b").select("a", "b", "ta", "tb")

    def run(batches):
        hashes, text, held = WordHashes(), None, None
        for batch in sliced(batches):
            found = []
            for ta, tb in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist()):
                if tb != text:
                    text, held = tb, shingle_set(tb, hashes, width)
                found.append(links_exactly(shingle_set(ta, hashes, width), held, percent))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["a", "b"]).filter(pa.array(found, pa.bool_()))

    return rows.mapInArrow(run, "a long, b long")


def _band(n: Column) -> Column:
    return F.floor(F.log(n) / F.lit(float(np.log(BAND))) + F.lit(1e-9)).cast("int")


def _least_shared(least: tuple[Column, Column], most: tuple[Column, Column], percent: int) -> Column:
    """Entries that two groups share at least if they hold a link."""
    common = F.ceil((least[0] + least[1]) * F.lit(percent) / F.lit(100.0 + percent) - F.lit(1e-6))
    behind = [F.ceil(m * F.lit(percent) / F.lit(100.0) - F.lit(1e-6)) - 1 for m in most]
    return F.greatest(F.lit(1), F.least(common - behind[0], common - behind[1]))


def _sets(docs: DataFrame, ids: DataFrame, width: int) -> DataFrame:
    """(_id, toks) of the documents among ``ids`` (and some more), as binary token sets."""

    def run(batches):
        hashes = WordHashes()
        for batch in sliced(batches):
            toks = [shingle_set(t, hashes, width).tobytes() for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(toks, pa.binary())], ["_id", "toks"])

    return rows_with(docs, ids, "_id").mapInArrow(run, "_id long, toks binary")


def _opened(docs: DataFrame, known: DataFrame, opened: DataFrame, width: int, percent: int) -> DataFrame:
    """Links (a, b) between the members of opened group pairs.

    Members of small groups are paired. A group of more than ``BLOCK`` members is kept in blocks of about that
    many, and each member of the smaller group opens each block as one row; as a block's members are connected
    already, one link to it is all that is told.
    """
    member = known.select("root", _band(F.col("n")).alias("band"), "node", "n")
    size = member.groupBy("root", "band").agg(F.count(F.lit(1)).alias("size"))
    side = lambda df, x: df.select(*(F.col(c).alias(f"{c}_{x}") for c in df.columns))
    both = opened.select("root_a", "band_a", "root_b", "band_b").join(side(size, "a"), ["root_a", "band_a"]).join(side(size, "b"), ["root_b", "band_b"])
    turn = F.col("size_a") > F.col("size_b")
    pick = lambda c, x, y: F.when(turn, F.col(f"{c}_{y}")).otherwise(F.col(f"{c}_{x}"))
    both = both.select(*(pick(c, x, y).alias(f"{c}_{x}") for x, y in ("ab", "ba") for c in ("root", "band")), F.greatest("size_a", "size_b").alias("most"))
    both = written(both, "opened")
    fits = (F.col("n_a") * 100 >= F.col("n_b") * percent) & (F.col("n_b") * 100 >= F.col("n_a") * percent)
    small = both.where(F.col("most") <= BLOCK).join(side(member, "a"), ["root_a", "band_a"]).join(side(member, "b"), ["root_b", "band_b"]).where(fits)
    links = _verified(docs, small.select(F.col("node_a").alias("a"), F.col("node_b").alias("b")), width, percent)

    wide = both.where(F.col("most") > BLOCK)
    inside = written(side(member, "b").join(wide.select("root_b", "band_b", "most").distinct(), ["root_b", "band_b"]).withColumn("block", F.pmod(F.xxhash64("node_b"), F.ceil(F.col("most") / BLOCK))), "block-members")
    blocks = inside.join(_sets(docs, inside.select(F.col("node_b").alias("_id")), width).withColumnRenamed("_id", "node_b"), "node_b")
    blocks = blocks.groupBy("root_b", "band_b", "block").agg(F.collect_list(F.struct("node_b", "toks")).alias("members"))
    asks = written(wide.select("root_a", "band_a", "root_b", "band_b").join(side(member, "a"), ["root_a", "band_a"]).select("node_a", "root_b", "band_b"), "asks")
    asks = asks.join(_sets(docs, asks.select(F.col("node_a").alias("_id")), width).withColumnRenamed("_id", "node_a").withColumnRenamed("toks", "own"), "node_a")
    rows = asks.join(blocks.hint("merge"), ["root_b", "band_b"]).select("node_a", "own", "members")

    def run(batches):
        for batch in sliced(batches):
            found = ([], [])
            for node, own, members in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                own = np.frombuffer(own, np.uint64)
                for x in members:
                    if links_exactly(own, np.frombuffer(x["toks"], np.uint64), percent):
                        found[0].append(node)
                        found[1].append(x["node_b"])
                        break
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in found], ["a", "b"])

    return links.unionByName(rows.mapInArrow(run, "a long, b long"))


def join(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, percent: int = PERCENT) -> DataFrame:
    """doc_id, n_shingles, component_id for every row of ``docs``."""
    docs = docs.select(F.col(id_col).cast("long").alias("_id"), F.col(text_col).alias("_text"))
    made = written(_signatures(docs, width), "signatures")
    rows = made.where("kind = 0").drop("kind")
    minima = [f"m{i}" for i in range(MINIMA)]
    nodes = rows.where("n > 0 AND id IS NOT NULL").groupBy("sid", "n").agg(F.min("id").alias("node"), *(F.min(m).alias(m) for m in minima))
    nodes = written(nodes, "nodes")

    # 2. groups of similar documents
    near, known = None, nodes.withColumn("root", F.col("node"))
    for leads in LEADS:
        keys = known.select("node", "n", "root", F.posexplode(F.array(*minima)).alias("perm", "key"))
        order = {"node": F.col("node"), "hash": F.xxhash64("node", "perm")}
        picks = [F.struct(order[by].alias("by"), "node", "n", "root") for by, _ in leads]
        lead = keys.groupBy("perm", "key").agg(F.count(F.lit(1)).alias("size"), F.array(*((F.min if first else F.max)(x) for x, (_, first) in zip(picks, leads))).alias("leads"))
        lead = lead.where("size > 1").select("perm", "key", F.explode("leads").alias("lead"))
        tries = keys.join(lead.hint("merge"), ["perm", "key"]).where((F.col("root") != F.col("lead.root")) & (F.col("n") * 100 >= F.col("lead.n") * percent) & (F.col("lead.n") * 100 >= F.col("n") * percent))
        found = written(_verified(docs, tries.select(F.col("node").alias("a"), F.col("lead.node").alias("b")), width, percent), "near")
        near = found if near is None else near.unionByName(found)
        known = written(nodes.join(components(near), "node", "left").select("sid", "n", "node", *minima, F.coalesce("root", "node").alias("root")), "known")

    # 3. the token-group matrix
    level = np.zeros(1 << SKETCH_BITS, np.int8)
    sketch = made.where("kind = 1").groupBy("id").agg(F.log2(F.sum("n") + 1).cast("int").alias("level")).toArrow()  # at most 2**SKETCH_BITS rows
    level[sketch.column(0).to_numpy()] = sketch.column(1).to_numpy()
    firsts = _prefixes(docs, level, width, percent).join(known.select("sid", "n", "root").hint("merge"), ["sid", "n"])
    matrix = _entries(firsts).repartition("token")
    at = "OVER (PARTITION BY token)"
    matrix = matrix.select("*", F.expr(f"min(root) {at}").alias("lo"), F.expr(f"max(root) {at}").alias("hi")).where("lo != hi")
    least, most = F.shiftright("span", 32), F.col("span").bitwiseAND(0xFFFFFFFF)
    matrix = matrix.select("token", "root", _band(least).alias("band"), least.alias("least"), most.alias("most"))
    matrix = written(matrix.groupBy("token", "root", "band").agg(F.min("least").alias("least"), F.max("most").alias("most")), "matrix")

    # 4. bound and open
    reach = int(np.ceil(np.log(100 / percent) / np.log(BAND))) + 1
    a, b = (matrix.select("token", *(F.col(c).alias(f"{c}_{side}") for c in ("root", "band", "least", "most"))) for side in "ab")
    fits = (F.col("root_a") < F.col("root_b")) & (F.abs(F.col("band_a") - F.col("band_b")) <= reach) & (F.col("most_a") * 100 >= F.col("least_b") * percent) & (F.col("most_b") * 100 >= F.col("least_a") * percent)
    shared = a.join(b, "token").where(fits).groupBy("root_a", "band_a", "root_b", "band_b").agg(F.count(F.lit(1)).alias("shared"), *(f(c).alias(c) for c, f in (("least_a", F.min), ("least_b", F.min), ("most_a", F.max), ("most_b", F.max))))
    opened = shared.where(F.col("shared") >= _least_shared((F.col("least_a"), F.col("least_b")), (F.col("most_a"), F.col("most_b")), percent))
    far = _opened(docs, known, opened, width, percent)

    # 5. components
    links = near.unionByName(far)
    final = components(links)
    label = nodes.select("sid", "n", "node").join(final, "node", "left").select("sid", "n", F.coalesce("root", "node").alias("root"))
    out = rows.select("id", "sid", "n").join(label, ["sid", "n"], "left")
    return out.select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), F.when(F.col("id").isNotNull(), F.coalesce("root", "id")).alias("component_id"))


def kept_rows(docs: DataFrame, **options) -> DataFrame:
    """One row of each component stays, the one with the smallest id; rows with a null id stay."""
    found = written(join(docs, **options), "components")
    lost = found.where("component_id != doc_id").select("doc_id")
    return rows_without(docs, lost, "doc_id")
