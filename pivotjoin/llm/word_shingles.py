"""Near-duplicates of texts: SimHash fingerprints and their index on byte positions propose pairs, then bands of minima those
that differ in more bits; the whole shingle sets decide."""

from __future__ import annotations

from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import simhash
from .common import discard, materialize, tidy
from .graph import components

#: Words of a shingle, and the least Jaccard similarity of two documents that are linked, in percent.
SHINGLE, PERCENT = 5, 80
#: A pair of similarity s shares a band with probability 1 - (1 - s**ROWS)**BANDS: 0.99993 at 0.8.
BANDS, ROWS = 24, 5
#: Rounds in which the rows of a band are compared with one leader only.
ROUNDS = 2
#: Shingles whose minima are taken at once.
CHUNK = 1 << 10
SEED = 42
#: Bits of a set's signature, and of the bitmap that tells whose sets are needed.
SIGNATURE, WANTED_BITS = 512, 1 << 26
#: Odd multipliers that spread bits.
SPREAD, SPREAD_2, SPREAD_32 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint32(0x85EBCA6B)


def _folded(columns: list[np.ndarray]) -> np.ndarray:
    """A 64-bit hash of each row of equal columns."""
    x = columns[0].copy()
    for c in columns[1:]:
        x *= SPREAD
        x ^= x >> np.uint64(32)
        x += c
    for m, shift in ((SPREAD_2, 31), (SPREAD, 29)):
        x *= m
        x ^= x >> np.uint64(shift)
    return x


def shingles(text: bytes | None, width: int = SHINGLE) -> np.ndarray:
    """Hashes of the distinct shingles of a text in UTF-8, sorted; fewer words than ``width`` are one shingle, no word none."""
    words = (text or b"").lower().split()
    if not words:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
    k = min(width, len(words))
    n = len(words) - k + 1
    return np.unique(_folded([np.full(n, k, np.uint64), *(h[j : j + n] for j in range(k))]))


@cache
def _factors(n: int) -> tuple[np.ndarray, np.ndarray]:
    g = np.random.default_rng(SEED)
    return g.integers(0, 1 << 31, (n, 1), np.uint32) * np.uint32(2) + np.uint32(1), g.integers(0, 1 << 32, (n, 1), np.uint32)


def band_keys(x: np.ndarray, bands: int = BANDS, rows: int = ROWS) -> np.ndarray:
    """A key for each band, from the minima of bands * rows hash functions; no key for an empty set."""
    if not len(x):
        return np.empty(0, np.int64)
    a, b = _factors(bands * rows)
    high = (x >> np.uint64(32)).astype(np.uint32)
    least = np.full(bands * rows, np.iinfo(np.uint32).max, np.uint32)
    for at in range(0, len(high), CHUNK):
        y = (high[None, at : at + CHUNK] ^ b) * a
        y ^= y >> np.uint32(15)
        y *= SPREAD_32
        np.minimum(least, y.min(axis=1), out=least)
    return _folded([np.arange(bands, dtype=np.uint64), *least.reshape(bands, rows).T.astype(np.uint64)]).view(np.int64)


def _node(x: np.ndarray) -> int:
    """A hash of a shingle set as a signed long, so that equal sets are one node."""
    return xxhash.xxh64_intdigest(x.tobytes()) - (1 << 63)


def _prints(docs: DataFrame, id_col: str, text_col: str, width: int) -> DataFrame:
    """(doc_id, fp, node, n, keys) of each document: its SimHash fingerprint (see ``simhash.fingerprint``), its set's hash, size and bands."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            prints, nodes, sizes, keys = [], [], [], []
            for t in b.column(1).cast(pa.binary()):
                text = t.as_py()
                x = shingles(text, width)
                prints.append(simhash.fingerprint(text))
                nodes.append(_node(x))
                sizes.append(len(x))
                keys.append(band_keys(x))
            fps = pa.array(np.array(prints, np.uint64).view(np.int64))
            yield pa.RecordBatch.from_arrays([b.column(0), fps, pa.array(nodes, pa.int64()), pa.array(sizes, pa.int64()), pa.array(keys, pa.list_(pa.int64()))], ["doc_id", "fp", "node", "n", "keys"])

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(tidy(run), "doc_id long, fp long, node long, n long, keys array<long>")


def signature(x: np.ndarray) -> np.ndarray:
    """SIGNATURE bits as longs: each tells if an odd number of hashes falls on it, so sets of k different members differ in at most k bits."""
    return np.packbits(np.bincount((x % np.uint64(SIGNATURE)).astype(np.int64), minlength=SIGNATURE).astype(np.uint8) & 1, bitorder="little").view(np.int64)


def _place(node: Column, doc_id: Column) -> Column:
    return node.bitwiseXOR(F.coalesce(doc_id, F.lit(0).cast("long"))).bitwiseAND(F.lit(WANTED_BITS - 1))


def _sets(docs: DataFrame, wanted: DataFrame, id_col: str, text_col: str, width: int) -> DataFrame:
    """(node, items, bits): whole shingle sets of the wanted (node, least), with signatures; of few others too.

    The wanted ones are marked in a bitmap of fixed size, so that the sets of the other documents are not sent.
    """
    place = _place(F.col("node"), F.col("least"))
    marks = wanted.groupBy(F.shiftright(place, 6).alias("at")).agg(F.bit_or(F.expr("shiftleft(1L, cast((node ^ coalesce(least, 0L)) & 63 as int))")).alias("bits")).toArrow()  # at most WANTED_BITS / 64 rows
    bitmap = np.zeros(WANTED_BITS // 64, np.int64)
    bitmap[marks.column("at").to_numpy()] = marks.column("bits").to_numpy()
    shared = docs.sparkSession.sparkContext.broadcast(bitmap)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        marked = shared.value
        for b in batches:
            nodes, items, bits = [], [], []
            for i, t in zip(b.column(0).to_pylist(), b.column(1).cast(pa.binary()), strict=True):
                x = shingles(t.as_py(), width)
                node = _node(x)
                at = (node ^ (i or 0)) & WANTED_BITS - 1
                if int(marked[at >> 6]) >> (at & 63) & 1:
                    nodes.append(node)
                    items.append(x.view(np.int64))
                    bits.append(signature(x))
                if len(nodes) == 256:
                    yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array(items, pa.list_(pa.int64())), pa.array(bits, pa.list_(pa.int64()))], ["node", "items", "bits"])
                    nodes, items, bits = [], [], []
            yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array(items, pa.list_(pa.int64())), pa.array(bits, pa.list_(pa.int64()))], ["node", "items", "bits"])

    sets = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(tidy(run), "node long, items array<long>, bits array<long>")
    return sets.dropDuplicates(["node"])


def verified(pairs: DataFrame, sets: DataFrame, percent: int = PERCENT) -> DataFrame:
    """Those (u, v) whose sets have a Jaccard similarity of percent / 100 or more, in whole numbers."""
    x = pairs.join(sets.select(F.col("node").alias("u"), F.col("items").alias("a")), "u")
    x = x.join(sets.select(F.col("node").alias("v"), F.col("items").alias("b")), "v")
    size = lambda c: F.size(c).cast("long")
    return x.where(size(F.array_intersect("a", "b")) * (100 + percent) >= (size("a") + size("b")) * percent).select("u", "v")


def close_pairs(sets: DataFrame, nodes: DataFrame, percent: int = PERCENT) -> DataFrame:
    """(u, v) of all nodes (node, root, n) of different roots that can have the similarity; none that has it is missing.

    Shingles are ordered by how many of these nodes hold them, those of one root alone first. Two
    sets that are similar enough share one of their first n - ceil(n percent / 100) + 1, and what comes after it in
    both must suffice. Signatures rule out most of the rest: similar sets differ in few members.
    """
    each = sets.join(nodes, "node").select("node", "root", "n", "bits", F.explode("items").alias("t"))
    shared = materialize(each.groupBy("t").agg(F.count(F.lit(1)).alias("c"), F.min("root").alias("a"), F.max("root").alias("b")).where("a <> b").select("t", "c"))
    listed = each.join(shared, "t").groupBy("node").agg(F.first("root").alias("root"), F.first("n").alias("n"), F.first("bits").alias("bits"), F.array_sort(F.collect_list(F.struct("c", "t"))).alias("s"))
    alone = F.col("n") - F.size("s")  # these come first and meet no other root
    prefix = F.col("n") - F.ceil(F.col("n") * percent / F.lit(100)).cast("long") + 1
    posted = listed.where(prefix > alone).select("node", "root", "n", "bits", alone.alias("alone"), F.posexplode(F.slice("s", F.lit(1), (prefix - alone).cast("int"))).alias("at", "s"))
    posted = materialize(posted.select(F.col("s.t").alias("t"), "node", "root", "n", "bits", (F.col("alone") + F.col("at")).alias("at")))
    x, y = posted.alias("x"), posted.alias("y")
    both = F.col("x.n") + F.col("y.n")
    rest = F.least(F.col("x.n") - F.col("x.at"), F.col("y.n") - F.col("y.at"))
    differ = sum((F.bit_count(F.col("x.bits")[i].bitwiseXOR(F.col("y.bits")[i])) for i in range(SIGNATURE // 64)), F.lit(0))
    on = (F.col("x.t") == F.col("y.t")) & (F.col("x.node") < F.col("y.node")) & (F.col("x.root") != F.col("y.root")) & _close(F.col("x.n"), F.col("y.n"), percent)
    on = on & (rest * (100 + percent) >= both * percent) & (differ * (100 + percent) <= both * (100 - percent))
    return x.join(y, on).select(F.col("x.node").alias("u"), F.col("y.node").alias("v")).distinct()


def _close(n: Column, m: Column, percent: int) -> Column:
    return F.least(n, m) * 100 >= F.greatest(n, m) * percent


def print_pairs(prints: DataFrame, rows: int | None = None) -> DataFrame:
    """(u, v) of nodes, from (fp, node): pairs that SimHash finds, not yet verified.

    Nodes of equal fingerprints meet the smallest one of these; fingerprints within the distance are found by the
    inverted index on byte positions (``simhash.near_links``), where a posting list gives a forest, and their smallest nodes meet.
    ``rows``: a bound of the rows of ``prints``, if known.
    """
    each = materialize(prints.select("fp", "node").distinct(), rows)
    reps = materialize(each.groupBy("fp").agg(F.min("node").alias("rep")), rows)
    equal = each.join(reps, "fp").where("node <> rep").select(F.col("rep").alias("u"), F.col("node").alias("v"))
    near = simhash.near_links(reps.select("fp"), rows=rows)
    x, y = (reps.select(F.col("fp").alias(c), F.col("rep").alias(f"rep_{c}")) for c in "uv")
    near = near.join(x, "u").join(y, "v").where("rep_u <> rep_v").select(F.least("rep_u", "rep_v").alias("u"), F.greatest("rep_u", "rep_v").alias("v"))
    found = materialize(equal.unionByName(near).distinct(), rows and rows * (1 + len(simhash.TRIPLES)))
    discard(each, reps)
    return found


def near_links(posted: DataFrame, sets: DataFrame, percent: int = PERCENT, rounds: int = ROUNDS, rows: int | None = None, links: DataFrame | None = None) -> DataFrame:
    """(node, root) of all nodes that share a band with another or have one of ``links``, verified pairs (u, v) that are known: components of all verified pairs.

    What the known links join is one component from the start. At first the rows of a band are compared with one leader, in every round with another one; what
    a large group of copies consists of is one component after that. Then all nodes that share a
    band with one of another component are joined by ``close_pairs``, so no pair that shares a band is left out.
    ``rows``: a bound of the rows of ``posted`` and of ``links``, if known.
    """
    known, roots = links, None
    rooted = posted.select("key", "node", "n", F.col("node").alias("root"))
    if known is not None:
        roots = components(known, rows)
        rooted = posted.join(roots, "node", "left").select("key", "node", "n", F.coalesce("root", "node").alias("root"))
    for at in range(rounds + 1):
        lead = F.min(F.struct(F.xxhash64(F.lit(at), "node").alias("h"), "node", "root", "n")).alias("lead")
        open_keys = materialize(rooted.groupBy("key").agg(F.min("root").alias("a"), F.max("root").alias("b"), lead).where("a <> b").select("key", "lead"), rows)
        rooted = rooted.join(open_keys, "key")
        if at < rounds:
            pairs = rooted.where((F.col("root") != F.col("lead.root")) & _close(F.col("n"), F.col("lead.n"), percent)).select(F.least("node", "lead.node").alias("u"), F.greatest("node", "lead.node").alias("v")).distinct()
            pairs = materialize(pairs, rows)  # each row makes one at most
        else:
            pairs = materialize(close_pairs(sets, materialize(rooted.select("node", "root", "n").distinct(), rows), percent))
        found = materialize(verified(pairs, sets, percent), rows if at < rounds else None)
        discard(pairs, open_keys)
        links = found if links is None else links.unionByName(found)
        roots = components(links, rows and rows * (at + 1 + (known is not None)) if at < rounds else None)
        rooted = posted.join(roots, "node", "left").select("key", "node", "n", F.coalesce("root", "node").alias("root"))
    return roots


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """(doc_id, component_id): every document with the smallest id it is linked to, directly or through others.

    SimHash fingerprints, their inverted index, tally and distance find pairs first (``print_pairs``), and sets verify them. A pair of the
    least similarity differs in more bits than an index on bytes can bear, so bands then propose what fingerprints have not linked.
    Texts with equal sets, those without words (null, empty, white space) among them, are linked;
    a null id stands in no other document's component and its row is returned too; repeated rows
    share a component; texts of any length count whole; an empty table gives no rows.
    """
    prints = materialize(_prints(docs, id_col, text_col, width))
    rows = prints.count()
    reps = materialize(prints.groupBy("node").agg(F.min("doc_id").alias("least"), F.first("n").alias("n"), F.first("keys").alias("keys")), rows)
    each = reps.select("node", "n", F.explode("keys").alias("key"))
    shared = materialize(each.groupBy("key").agg(F.count(F.lit(1)).alias("c")).where("c > 1").select("key"), BANDS * rows)
    posted = materialize(each.join(shared, "key"), BANDS * rows)
    close = print_pairs(prints, rows)
    ends = close.select(F.col("u").alias("node")).unionByName(close.select(F.col("v").alias("node")))
    wanted = materialize(posted.select("node").unionByName(ends).distinct().join(reps.select("node", "least"), "node"), rows)
    # one document of each set: others with the same set need not be sent
    sets = materialize(_sets(docs, wanted, id_col, text_col, width))
    links = materialize(verified(close, sets, percent), BANDS * rows)
    roots = near_links(posted, sets, percent, rows=BANDS * rows, links=links)
    classes = materialize(reps.join(roots, "node", "left").select("node", F.coalesce("root", "node").alias("root"), "least"), rows)
    tops = materialize(classes.groupBy("root").agg(F.min("least").alias("component_id")), rows)
    found = materialize(classes.join(tops, "root").select("node", "component_id"), rows)
    discard(shared, posted, close, wanted, sets, links, reps, classes, tops)
    return prints.join(found, "node").select("doc_id", "component_id")
