"""Exact self-join on n-gram Jaccard similarity by parity sketches, and its connected components.

Sets of distinct k-word shingles (64-bit hashes of whole texts) are treated by size bands that grow by
1/t, so partners lie in the same or in neighbouring bands. If J(A, B) >= t and A is the smaller set, then
|A xor B| <= (1-t)/t * |A|; a band's bound d holds for all pairs whose smaller set lies in it. A band's
sketch is a bit vector in which every shingle flips one bit, so the Hamming distance of two sketches never
exceeds the size of the symmetric difference. It is cut in m > d words, of which by the pigeonhole principle
at least m - d are equal in a linked pair; m is chosen for the band, so that a word gets a few shingles, and words
are WORD_BITS long, so that those few bits seldom agree by chance. Such sketches are sparse: a word is kept
as the XOR of a hash of each odd bit's number, which is the same for equal words. Each set is entered under
the words of its own band's sketch and of the band's below. Empty words, which say nothing, are left out where
a set has fewer than m - d of them, since then one of the equal words is filled; m is chosen so that this is the rule.

Equal sets share one hash and are one class from the start. Class ids, not documents, meet in the join, and a task
enters a class once, however many copies it reads: n copies cost at most one entry a key in each task. In each
bucket first everything is held against one pivot, and linked
classes are merged; then only pairs from different components are compared, by their sketches inside a
task, which gives out the few that pass. So linked copies cost their number and not its square, no pair of a
bucket becomes a row before it has passed, and no link between different components is lost. Candidates pass a
check of sizes and of a second, dense parity sketch before the shingle sets are compared exactly.

Defined cases: null, empty and blank texts have the empty set, 0 shingles, and are linked with nothing;
texts with fewer than k words have one shingle; a row whose id is null is in its class's component (null if
only such rows are in it); rows with one id stand for one document; extra columns are ignored; an empty
table gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import forget, release, small, stored

#: Words of a vocabulary kept in a worker's memo; longest word (bytes) kept there; classes that a task remembers to have entered.
MEMO, WORD, ENTERED = 200_000, 64, 500_000
#: Bits of a word of the sketches that are joined; most bits of the dense ones, which longer sets fold onto.
WORD_BITS, DENSE_BITS = 1 << 32, 1 << 17
#: Rows of a bucket that meet in one task at most, against as many others.
CHUNK = 4096
MIX = np.uint64(0x9E3779B97F4A7C15)
LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))


@dataclass(frozen=True)
class Rule:
    """Shingle length in words and threshold percent / 100: linked when 100 * |A & B| >= percent * |A | B|."""

    words: int = 4
    percent: int = 85

    @property
    def bands(self) -> list[int]:
        """Lower ends of the size bands; sizes beyond the last follow the same growth."""
        ends = [1]
        while ends[-1] < 1 << 40:
            ends.append(max(ends[-1] + 1, math.ceil(ends[-1] * 100 / self.percent)))
        return ends

    def allowance(self, band: int) -> int:
        """Largest symmetric difference of a linked pair whose smaller set lies in the band."""
        return (100 - self.percent) * (self.bands_cached[band + 1] - 1) // self.percent

    def words_of(self, band: int) -> int:
        """Words of a band's sketch: its allowance, and more than a set of the band's least size is likely to leave empty."""
        if (self, band) not in _words:
            d, least = self.allowance(band), self.bands_cached[band]
            m = d + 1
            while True:
                empty = m * math.exp(-least / m)
                if m - d >= empty + 2 * math.sqrt(empty) + 1:
                    break
                m += 1
                if m > 2 * d + 8:
                    break
            _words[self, band] = m
        return _words[self, band]

    @property
    def bands_cached(self) -> list[int]:
        if self not in _bands:
            _bands[self] = self.bands
        return _bands[self]


_bands: dict[Rule, list[int]] = {}
_words: dict[tuple[Rule, int], int] = {}


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64-bit words."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Shingler:
    """Sorted distinct shingle hashes of a text; words are runs free of ASCII white space, A-Z in lower case."""

    def __init__(self, k: int):
        self.k, self.memo = k, {}

    def word(self, w: bytes) -> int:
        h = xxhash.xxh3_64_intdigest(w)
        if len(w) <= WORD:
            self.memo[w] = h
        return h

    def __call__(self, text: str | None) -> np.ndarray:
        words = (text or "").encode("utf-8", "surrogatepass").translate(LOWER).split()
        if not words:
            return np.empty(0, np.uint64)
        if len(self.memo) > MEMO:
            self.memo.clear()
        get, new = self.memo.get, self.word
        hashes = np.array([get(w) or new(w) for w in words], np.uint64)
        n = max(1, len(words) - self.k + 1)
        with np.errstate(over="ignore"):
            out = np.full(n, MIX * np.uint64(min(len(words), self.k)), np.uint64)
            for i in range(min(self.k, len(words))):
                out = mixed(out + hashes[i : i + n]) * MIX
        return np.unique(out)


def sketch(shingles: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray]:
    """Parity sketch of so many words of WORD_BITS bits: the XOR of a hash of the number of each odd bit, per word; and which words have any."""
    with np.errstate(over="ignore"):
        h = mixed(shingles + np.uint64(words) * MIX)
        cell = (((h >> np.uint64(32)) * np.uint64(words)) >> np.uint64(32)).astype(np.int64)
        bit = mixed(h + MIX) & np.uint64(WORD_BITS - 1)
        value = mixed(bit * MIX + MIX)  # two shingles on one bit take each other out
    out = np.zeros(words, np.uint64)
    np.bitwise_xor.at(out, cell, value)
    return out, out != 0


def entries(shingles: np.ndarray, rule: Rule) -> np.ndarray:
    """Keys under which a set is entered."""
    bands = rule.bands_cached
    own = int(np.searchsorted(bands, len(shingles), side="right")) - 1
    keys = []
    for band in (own, own - 1):
        if band < 0 or (d := rule.allowance(band)) == 0:
            continue  # only equal sets link there
        m = rule.words_of(band)
        w, filled = sketch(shingles, m)
        with np.errstate(over="ignore"):
            key = mixed(w + mixed(np.arange(m, dtype=np.uint64) * MIX + np.uint64(band + 1)))
        # at least m - d words are equal in a linked set: with fewer empty ones than that, one of them is filled
        keys.append(key[filled] if m - int(filled.sum()) < m - d else key)
    return np.unique(np.concatenate(keys)) if keys else np.empty(0, np.uint64)


def set_hash(shingles: np.ndarray) -> int:
    return xxhash.xxh3_64_intdigest(shingles.tobytes()) - (1 << 63)


def whole_sketch(shingles: np.ndarray) -> bytes:
    """Dense parity sketch: two to four bits per shingle up to DENSE_BITS, a power of two of 64-bit words, so that larger ones fold onto smaller ones."""
    h = mixed(shingles)
    bits = min(DENSE_BITS, 64 << ((len(shingles) - 1) // 32).bit_length())
    at = h & np.uint64(bits - 1)
    out = np.zeros(bits // 64, np.uint64)
    np.bitwise_xor.at(out, (at >> np.uint64(6)).astype(np.int64), np.uint64(1) << (at & np.uint64(63)))
    return out.tobytes()


def folded_distance(a: bytes, b: bytes) -> int:
    x, y = np.frombuffer(a, np.uint64), np.frombuffer(b, np.uint64)
    if len(x) > len(y):
        x = np.bitwise_xor.reduce(x.reshape(-1, len(y)), axis=0)
    elif len(y) > len(x):
        y = np.bitwise_xor.reduce(y.reshape(-1, len(x)), axis=0)
    return int(np.bitwise_count(x ^ y).sum())


def _signed(a: np.ndarray) -> np.ndarray:
    return a.view(np.int64)


def _sets(docs: DataFrame, rule: Rule, what: str) -> DataFrame:
    """docs(id, text) through the shingler. what: 'size' (with hash and sketch), 'keys' (hash and entries) or 'set' (hash and shingles).

    Entries are made anew from the texts, since a stored copy of them would be as large as the texts.
    """
    kind = docs.schema[0].dataType.simpleString()
    schema = {"size": f"id {kind}, n long, cls long, sk binary", "keys": "cls long, keys array<long>", "set": "cls long, shingles array<long>"}[what]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler(rule.words)
        entered: set[int] = set()
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                sets = map(shingler, part.column(1).to_pylist())
                if what == "size":
                    n, cls, sk = zip(*[(len(s), set_hash(s), whole_sketch(s) if len(s) else None) for s in sets])
                    yield pa.RecordBatch.from_arrays([part.column(0), pa.array(n, pa.int64()), pa.array(cls, pa.int64()), pa.array(sk, pa.binary())], ["id", "n", "cls", "sk"])
                    continue
                cls, offsets, values = [], [0], []
                for s in sets:
                    c = set_hash(s)
                    if what == "keys":
                        if c in entered:
                            continue
                        if len(entered) >= ENTERED:
                            entered.clear()
                        entered.add(c)
                    cls.append(c)
                    values.append(_signed(entries(s, rule) if what == "keys" else s))
                    offsets.append(offsets[-1] + len(values[-1]))
                lists = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(np.concatenate(values) if values else np.empty(0, np.int64), pa.int64()))
                yield pa.RecordBatch.from_arrays([pa.array(cls, pa.int64()), lists], ["cls", "keys" if what == "keys" else "shingles"])
        release()

    return docs.mapInArrow(run, schema)


def _across(rule: Rule):
    """Rows (key, lo, hi, chunk, cls, comp, n, sk), those of one (key, lo, hi) together, to pairs (a, b) of different components that pass the checks of sizes and sketches.

    Nothing but such pairs leaves the task; a group has at most two chunks of CHUNK rows.
    """

    def pairs(rows: pa.Table) -> pa.RecordBatch:
        key, lo, hi, chunk, cls, comp, n = (rows.column(i).to_numpy() for i in range(7))
        blobs = rows.column(7).to_pylist()
        width = np.array([len(b) // 8 for b in blobs])
        place, m = np.zeros(len(blobs), np.int64), {}  # sketches of one width together
        for w in np.unique(width):
            at = np.flatnonzero(width == w)
            place[at] = np.arange(len(at))
            m[int(w)] = np.frombuffer(b"".join([blobs[i] for i in at]), np.uint64).reshape(len(at), w)
        new = np.r_[True, (key[1:] != key[:-1]) | (lo[1:] != lo[:-1]) | (hi[1:] != hi[:-1])]
        group = np.cumsum(new)
        size = np.diff(np.r_[np.flatnonzero(new), len(key)])
        out: list[np.ndarray] = [np.empty((0, 2), np.int64)]
        for step in range(1, int(size.max(initial=1))):
            i = np.flatnonzero(group[step:] == group[:-step])
            j = i + step
            ok = (comp[i] != comp[j]) & ((lo[i] == hi[i]) | (chunk[i] != chunk[j])) & (np.maximum(n[i], n[j]) * rule.percent <= np.minimum(n[i], n[j]) * 100)
            i, j = i[ok], j[ok]
            if not len(i):
                continue
            swap = width[i] < width[j]
            i, j = np.where(swap, j, i), np.where(swap, i, j)  # i has the wider sketch
            most = (100 - rule.percent) * (n[i] + n[j]) // (100 + rule.percent)
            for w in np.unique(width[j]):
                for v in np.unique(width[i][width[j] == w]):
                    at = np.flatnonzero((width[j] == w) & (width[i] == v))
                    for part in range(0, len(at), 1 << 14):
                        k = at[part : part + (1 << 14)]
                        x = np.bitwise_xor.reduce(m[int(v)][place[i[k]]].reshape(len(k), v // w, w), axis=1) ^ m[int(w)][place[j[k]]]
                        near = k[np.bitwise_count(x).sum(axis=1) <= most[k]]
                        if len(near):
                            a, b = cls[i[near]], cls[j[near]]
                            out.append(np.stack([np.minimum(a, b), np.maximum(a, b)], axis=1))
        found = np.unique(np.concatenate(out), axis=0)
        return pa.RecordBatch.from_arrays([pa.array(found[:, 0]), pa.array(found[:, 1])], ["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: pa.Table | None = None
        for batch in batches:
            rows = pa.Table.from_batches([batch]) if kept is None else pa.concat_tables([kept, pa.Table.from_batches([batch])])
            if not rows.num_rows:
                continue
            key, lo, hi = (rows.column(i).to_numpy() for i in range(3))
            # the last group may go on in the next batch
            same = (key == key[-1]) & (lo == lo[-1]) & (hi == hi[-1])
            cut = int(np.argmax(same))
            if cut:
                yield pairs(rows.slice(0, cut))
            kept = rows.slice(cut).combine_chunks()
        if kept is not None and kept.num_rows:
            yield pairs(kept)

    return run


def _verified(pairs: DataFrame, classes: DataFrame, texts: DataFrame, rule: Rule) -> DataFrame:
    """Those of the pairs (a, b) of classes that are linked, by exact comparison of the sets."""
    side = lambda x: classes.select(F.col("cls").alias(x), F.col("n").alias(f"n{x}"), F.col("sk").alias(f"s{x}"), F.col("rep").alias(f"r{x}"))
    full = pairs.join(side("a"), "a").join(side("b"), "b")
    lo, hi = F.least("na", "nb"), F.greatest("na", "nb")
    full = full.where(hi * rule.percent <= lo * 100)

    def near(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b, na, nb, sa, sb = (batch.column(i).to_pylist() for i in range(6))
            # |A xor B| <= (100-p)/(100+p) * (|A| + |B|)
            keep = [folded_distance(x, y) * (100 + rule.percent) <= (100 - rule.percent) * (m + n) for m, n, x, y in zip(na, nb, sa, sb)]
            yield batch.filter(pa.array(keep, pa.bool_())).select(["a", "b", "ra", "rb"])

    close = stored(full.select("a", "b", "na", "nb", "sa", "sb", "ra", "rb").mapInArrow(near, f"a long, b long, ra {_kind(classes)}, rb {_kind(classes)}"), "near")
    needed = close.select(F.col("ra").alias("id")).union(close.select(F.col("rb").alias("id"))).distinct()
    needed = stored(needed, "needed")
    chosen = texts.join(small(needed, needed.count()), "id", "left_semi")
    sets = stored(_sets(chosen, rule, "set"), "sets")
    # the pivot's set meets its partners' sets: a row per pair
    both = close.select("a", "b").join(sets.select(F.col("cls").alias("a"), F.col("shingles").alias("x")), "a").join(sets.select(F.col("cls").alias("b"), F.col("shingles").alias("y")), "b")

    def linked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            xs, ys, keep = batch.column(2), batch.column(3), []
            for x, y in zip(xs, ys):
                x, y = x.values.to_numpy(), y.values.to_numpy()
                same = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(100 * same >= rule.percent * (len(x) + len(y) - same))
            yield batch.filter(pa.array(keep, pa.bool_())).select(["a", "b"])

    links = stored(both.select("a", "b", "x", "y").mapInArrow(linked, "a long, b long"), "links")
    forget(close, needed, sets)
    return links


def _kind(classes: DataFrame) -> str:
    return classes.schema["rep"].dataType.simpleString()


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, root) for every node that a link names: root is the component's smallest node.

    Alternates hooking each root to the smallest root next to it with pointer jumping; every round is a
    written table, and rounds grow with the logarithm of the longest path.
    """
    edges = stored(links.select(F.least(a, b).alias("u"), F.greatest(a, b).alias("v")).where("u < v").distinct(), "edges")
    if edges.isEmpty():
        return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
    label = stored(edges.select(F.col("v").alias("node"), F.col("u").alias("root")).union(edges.select("u", "u")).groupBy("node").agg(F.min("root").alias("root")), "label")
    while True:
        # pointer jumping to the end of each chain
        while True:
            up = label.select(F.col("node").alias("root"), F.col("root").alias("top"))
            nxt = stored(label.join(up, "root").select("node", F.col("top").alias("root"), (F.col("top") < F.col("root")).alias("moved")), "jump")
            moved = not nxt.where("moved").isEmpty()
            forget(label)
            label = nxt.drop("moved")
            label._stored_path = nxt._stored_path
            if not moved:
                break
        l1, l2 = label.select(F.col("node").alias("u"), F.col("root").alias("ru")), label.select(F.col("node").alias("v"), F.col("root").alias("rv"))
        across = stored(edges.join(l1, "u").join(l2, "v").where("ru <> rv").select(F.least("ru", "rv").alias("lo"), F.greatest("ru", "rv").alias("hi")).distinct(), "across")
        if across.isEmpty():
            forget(across, edges)
            return label
        hook = across.groupBy(F.col("hi").alias("root")).agg(F.min("lo").alias("to"))
        nxt = stored(label.join(hook, "root", "left").select("node", F.coalesce(F.least("root", "to"), "root").alias("root")), "hook")
        # links between roots replace those between nodes: both ends of a root's links are roots
        forget(label, edges)
        label, edges = nxt, across.select(F.col("lo").alias("u"), F.col("hi").alias("v"))
        edges._stored_path = across._stored_path


def near_duplicates(docs: DataFrame, rule: Rule = Rule(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, n_shingles, class_id (hash of the set, null for empty ones), component_id. All of it runs when this is called; its tables are small against the texts."""
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    sizes = stored(_sets(texts, rule, "size"), "sizes")
    classes = stored(sizes.where("n > 0 and id is not null").groupBy("cls").agg(F.min("id").alias("rep"), F.first("n").alias("n"), F.first("sk").alias("sk")), "classes")
    bucket = Window.partitionBy("key")
    keys = _sets(texts, rule, "keys").select(F.explode("keys").alias("key"), "cls")
    # copies drop out, and lonely entries, in the sort of one shuffle
    keys = keys.withColumn("_before", F.lag("cls").over(bucket.orderBy("cls"))).where("_before is null or _before <> cls").select("key", "cls")
    met = stored(keys.withColumn("met", F.count("*").over(bucket)).where("met > 1"), "met")
    # the pivot of a bucket is its class that meets most others in all: the middle of a group, not one at its edge
    central = stored(met.groupBy("cls").agg(F.sum("met").alias("weight")), "central")
    heaviest = met.join(small(central, central.count()), "cls").groupBy("key").agg(F.max(F.struct("weight", "cls"))["cls"].alias("pivot"))
    shared = stored(met.select("key", "cls").join(heaviest, "key"), "shared")
    forget(met, central)
    pairs = stored(shared.where("cls <> pivot").select(F.least("pivot", "cls").alias("a"), F.greatest("pivot", "cls").alias("b")).distinct(), "pairs")
    links = _verified(pairs, classes, texts, rule)
    first = components(links)
    # second round: only pairs from different components can add anything
    named = shared.select("key", "cls").join(first.select(F.col("node").alias("cls"), F.col("root").alias("comp")), "cls", "left").select("key", "cls", F.coalesce("comp", "cls").alias("comp"))
    open_ = named.groupBy("key").agg(F.min("comp").alias("_lo"), F.max("comp").alias("_hi"), F.count("*").alias("_n")).where("_lo < _hi")
    named = named.join(open_.select("key", "_n"), "key")
    # buckets of many rows are cut in chunks, and every two chunks meet in a group of their own
    chunks = F.ceil(F.col("_n") / CHUNK)
    named = named.withColumn("chunk", F.pmod(F.xxhash64("cls"), chunks)).withColumn("_o", F.explode(F.sequence(F.lit(0).cast("long"), chunks - 1)))
    named = named.select("key", F.least("chunk", "_o").alias("lo"), F.greatest("chunk", "_o").alias("hi"), "chunk", "cls", "comp").join(classes.select("cls", "n", "sk"), "cls")
    dealt = named.repartition("key", "lo", "hi").sortWithinPartitions("key", "lo", "hi").select("key", "lo", "hi", "chunk", "cls", "comp", "n", "sk")
    left = stored(dealt.mapInArrow(_across(rule), "a long, b long").distinct(), "left")
    if not left.isEmpty():
        more = _verified(left, classes, texts, rule)
        both = stored(links.union(more), "all-links")
        forget(more, first)
        first = components(both)
        forget(both)
    forget(shared, pairs, links, left)
    comp = classes.select("cls", "rep").join(first.select(F.col("node").alias("cls"), "root"), "cls", "left").select("cls", "rep", F.coalesce("root", "cls").alias("root"))
    lowest = comp.groupBy("root").agg(F.min("rep").alias("component_id"))
    of_class = stored(comp.join(lowest, "root").select("cls", "component_id"), "of-class")
    full = sizes.where("n > 0").join(of_class, "cls", "left").select("id", "n", "cls", "component_id")
    empty = sizes.where("n = 0").select("id", "n", F.lit(None).cast("long").alias("cls"), F.col("id").alias("component_id"))
    out = stored(full.union(empty).select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), F.col("cls").alias("class_id"), "component_id"), "components")
    forget(sizes, classes, first, of_class)
    return out
