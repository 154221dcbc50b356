"""N-gram Jaccard join with a prefix tree, and its connected components.

Sets are the distinct five-word shingles of whole texts, as 64-bit fingerprints, in one global order: shingles of
seldom hit cells of a fixed count table over the whole corpus first, then by fingerprint. Sets that reach the
threshold share a shingle among the first n - ceil(3n/4) + 1 of each, and among the first n - ceil(6n/7) + 1 (the short
prefix) of the smaller one. An index of these prefixes gives candidates:

* a shingle that few sets have in their prefix gives its pairs, and as the number of shared prefix shingles bounds the
  overlap, pairs that share too few are dropped unseen;
* a shingle that many have gives a star: each set with one of them. Members that end in another component than the
  star's centre are paired with the rest of the shingle's sets, so that no link between components is lost. A star's
  members are dealt out, DEAL at a time, and what they are joined with is sent to each deal, so no task gets a whole star;
  places in the global order bound the overlap that a pair can have.

Candidates are verified by a prefix-tree join: the partners of a hub are a compressed trie of ordered sets, which the
hub's set descends, sharing the overlap of common paths and leaving subtrees whose sizes can't reach the threshold.
Equal sets are one class from the start and are never compared. Hot hubs are dealt over several tasks.

Null, empty and wordless texts have an empty set and link with nothing; rows that repeat an id are one node; rows with
a null id are their own (null) component and link with nothing.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .components import components
from .sieve import passes, sieve_of
from .storage import discard, materialise, send
from .textkernel import lean, shingle_sets, text_batches, tidy

WORDS = 5
#: Cells of the count table, as a power of two, and the parts it travels in.
CELL_BITS = 22
SLICES = 16
#: Prefix shingles of one part of the index, and of one flush of a task.
PART_SHINGLES = 1_500_000
FLUSH_SHINGLES = 1_000_000
#: Sets that share a prefix shingle: up to so many are paired, more become a star; beyond HOT a shingle is salted.
FEW = 24
HOT = 200_000
#: Partners of a hub that one task gets, and members of a star that are joined at a time.
PARTNERS = 128
DEAL = 500


def needed(a, b):
    """The smallest overlap of sets of a and b shingles with 100 * overlap >= 75 * union."""
    return -(-3 * (a + b) // 7)


def prefix_size(n):
    return n - -(-3 * n // 4) + 1


def short_size(n):
    """The prefix of a set that no larger or equal partner can miss, as the overlap is 6n/7 at least."""
    return n - -(-6 * n // 7) + 1


def order(grams: np.ndarray, cells: np.ndarray) -> np.ndarray:
    """A sorted set in the global order."""
    key = (np.minimum(cells[grams >> np.uint64(64 - CELL_BITS)], (1 << 24) - 1).astype(np.uint64) << np.uint64(40)) | (grams >> np.uint64(24))
    return grams[np.argsort(key, kind="stable")]


class Trie:
    """Ordered sets as a compressed trie over their common prefixes."""

    def __init__(self, members: list[tuple[int, np.ndarray]]):
        rows = sorted(members, key=lambda m: m[1].astype(">u8").tobytes())
        self.ids, self.sets = [m[0] for m in rows], [m[1] for m in rows]

    def _split(self, lo: int, hi: int, depth: int) -> int:
        """How far the sets lo..hi-1 agree from depth on."""
        first, last = self.sets[lo], self.sets[hi - 1]
        n = min(len(first), len(last))
        differ = np.flatnonzero(first[depth:n] != last[depth:n])
        return depth + int(differ[0]) if len(differ) else n

    def join(self, probe: np.ndarray) -> Iterator[tuple[int, int]]:
        """(id, overlap) of the members that reach the threshold with the probe."""
        lookup, size = np.sort(probe), len(probe)
        if not len(self.ids) or not size:
            return
        todo = [(0, len(self.ids), 0, 0)]
        while todo:
            lo, hi, depth, overlap = todo.pop()
            sizes = [len(s) for s in self.sets[lo:hi]]
            shared = self._split(lo, hi, depth)
            path = self.sets[lo][depth:shared]
            at = np.minimum(np.searchsorted(lookup, path), size - 1)
            overlap += int(np.count_nonzero(lookup[at] == path))
            if overlap + min(size - overlap, max(sizes) - shared) < needed(size, min(sizes)):
                continue
            while lo < hi and len(self.sets[lo]) == shared:
                if overlap >= needed(size, shared):
                    yield self.ids[lo], overlap
                lo += 1
            while lo < hi:
                token, end = self.sets[lo][shared], lo + 1
                while end < hi and self.sets[end][shared] == token:
                    end += 1
                todo.append((lo, end, shared, overlap))
                lo = end


def shingled(docs: DataFrame) -> DataFrame:
    """Rows of kind 0: doc_id, n, print of the set; of kind 1: a task's part of the count table."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zlib

        cells = np.zeros(1 << CELL_BITS, dtype=np.uint32)
        some = False
        for batch, texts in text_batches(batches):
            counts, prints = [], []
            for grams in shingle_sets(texts, WORDS):
                counts.append(len(grams))
                prints.append(hashlib.blake2b(grams.tobytes(), digest_size=16).digest() if len(grams) else None)
                cells[(grams >> np.uint64(64 - CELL_BITS)).astype(np.int64)] += 1  # a set hits a cell once
                some |= len(grams) > 0
            n = len(counts)
            yield pa.RecordBatch.from_arrays([pa.array([0] * n, pa.int32()), batch.column(0).cast(pa.int64()), pa.array(counts, pa.int64()), pa.array(prints, pa.binary()), pa.array([None] * n, pa.int32())], ["kind", "doc_id", "n", "print", "slice"])
        if some:
            parts = [zlib.compress(x.tobytes(), 1) for x in np.split(cells, SLICES)]
            yield pa.RecordBatch.from_arrays([pa.array([1] * SLICES, pa.int32()), pa.array([None] * SLICES, pa.int64()), pa.array([None] * SLICES, pa.int64()), pa.array(parts, pa.binary()), pa.array(range(SLICES), pa.int32())], ["kind", "doc_id", "n", "print", "slice"])

    return materialise(docs.mapInArrow(lean(run), "kind int, doc_id long, n long, print binary, slice int"), "sets", ("kind",))


def count_table(parts: DataFrame) -> np.ndarray:
    """The sum of all tasks' tables: 2**CELL_BITS counts, whatever the input."""
    import zlib

    def add(frame: pd.DataFrame) -> pd.DataFrame:
        total = np.zeros((1 << CELL_BITS) // SLICES, dtype=np.uint32)
        for blob in frame["print"]:
            total += np.frombuffer(zlib.decompress(blob), dtype=np.uint32)
        return pd.DataFrame({"slice": [int(frame["slice"].iloc[0])], "print": [zlib.compress(total.tobytes(), 1)]})

    out = np.zeros((SLICES, (1 << CELL_BITS) // SLICES), dtype=np.uint32)
    salted = parts.withColumn("salt", F.spark_partition_id() % 32)
    once = salted.select("slice", "print", "salt").groupBy("slice", "salt").applyInPandas(lambda f: add(f), "slice int, print binary")
    for r in once.groupBy("slice").applyInPandas(add, "slice int, print binary").toLocalIterator():
        out[r["slice"]] = np.frombuffer(zlib.decompress(r["print"]), dtype=np.uint32)
    return out.ravel()


def prefix_index(docs: DataFrame, shared, parts: int) -> DataFrame:
    """(part, grams, rows, places, ids, sizes): prefix shingles by part, each with its row in the lists of ids and set
    sizes and its place in the ordered set. A set that a task has had already is left out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        cells, salt = shared.value, TaskContext.get().partitionId()
        seen: set[bytes] = set()
        ids, sizes, grams, held = [], [], [], 0

        def flush() -> pa.RecordBatch:
            flat = np.concatenate(grams)
            held_by = np.array([len(g) for g in grams])
            rows = np.repeat(np.arange(len(ids)), held_by)
            place = (np.arange(len(flat)) - np.repeat(np.cumsum(held_by) - held_by, held_by)).astype(np.uint32)
            count = cells[(flat >> np.uint64(64 - CELL_BITS)).astype(np.int64)].astype(np.int64)
            part = (flat % np.uint64(parts)).astype(np.int64) + parts * (salt % (count // HOT + 1))
            by = np.argsort(part, kind="stable")
            names, begin = np.unique(part[by], return_index=True)
            out = []
            for p, at in zip(names.tolist(), np.split(by, begin[1:])):
                used, row = np.unique(rows[at], return_inverse=True)
                out.append((p, flat[at].tobytes(), row.astype(np.uint32).tobytes(), place[at].tobytes(), np.array(ids, dtype=np.int64)[used].tobytes(), np.array(sizes, dtype=np.uint32)[used].tobytes()))
            return pa.RecordBatch.from_arrays([pa.array([x[0] for x in out], pa.int64()), *(pa.array([x[i] for x in out], pa.binary()) for i in range(1, 6))], ["part", "grams", "rows", "places", "ids", "sizes"])

        for batch, texts in text_batches(batches):
            for key, full in zip(batch.column(0).to_pylist(), shingle_sets(texts, WORDS)):
                if key is None or not len(full) or (said := hashlib.blake2b(full.tobytes(), digest_size=16).digest()) in seen:
                    continue
                seen.add(said)
                ids.append(key)
                sizes.append(len(full))
                grams.append(order(full, cells)[: prefix_size(len(full))])
                held += len(grams[-1])
                if held >= FLUSH_SHINGLES:
                    yield flush()
                    ids, sizes, grams, held = [], [], [], 0
        if grams:
            yield flush()

    return docs.mapInArrow(lean(run), "part long, grams binary, rows binary, places binary, ids binary, sizes binary")


HITS = "gram long, a long, b long, na long, nb long, shared long, short boolean, at long, deal long"


def meet(index: DataFrame, shared) -> DataFrame:
    """From each part: pairs (gram null) with the number of shared prefix shingles, and members (gram, a, short, at, deal)
    of stars, with the shingle's place in the set and the deal of the star that the member is in."""

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        out = joined(frame)
        tidy()
        return out

    def joined(frame: pd.DataFrame) -> pd.DataFrame:
        cells, part = shared.value, int(frame["part"].iloc[0])
        ids, sizes, grams, rows, places, base = [], [], [], [], [], 0
        for r in frame.itertuples(index=False):
            ids.append(np.frombuffer(r.ids, dtype=np.int64))
            sizes.append(np.frombuffer(r.sizes, dtype=np.uint32))
            grams.append(np.frombuffer(r.grams, dtype=np.uint64))
            rows.append(np.frombuffer(r.rows, dtype=np.uint32).astype(np.int64) + base)
            places.append(np.frombuffer(r.places, dtype=np.uint32))
            base += len(ids[-1])
        key, size, gram, row, place = np.concatenate(ids), np.concatenate(sizes).astype(np.int64), np.concatenate(grams), np.concatenate(rows), np.concatenate(places).astype(np.int64)
        by = np.argsort(gram, kind="stable")
        gram, row, place = gram[by], row[by], place[by]
        short = place < short_size(size[row])
        begin = np.flatnonzero(np.concatenate(([True], gram[1:] != gram[:-1])))
        length = np.diff(np.append(begin, len(gram)))
        hot = cells[(gram[begin] >> np.uint64(64 - CELL_BITS)).astype(np.int64)] >= HOT
        found: dict[str, list] = {"pair": [], "times": []}
        for n in np.unique(length[(length > 1) & (length <= FEW) & ~hot]).tolist():
            starts = begin[(length == n) & ~hot]
            i, j = np.triu_indices(n, 1)
            for at in np.array_split(starts, max(1, len(starts) * len(i) // 2_000_000)):
                a, b = row[at[:, None] + i].ravel(), row[at[:, None] + j].ravel()
                fits = 4 * np.minimum(size[a], size[b]) >= 3 * np.maximum(size[a], size[b])
                a, b = a[fits], b[fits]
                pair, times = np.unique(np.minimum(a, b) * len(key) + np.maximum(a, b), return_counts=True)
                found["pair"].append(pair)
                found["times"].append(times)
        out = []
        if found["pair"]:
            pair, back = np.unique(np.concatenate(found["pair"]), return_inverse=True)
            times = np.bincount(back, weights=np.concatenate(found["times"])).astype(np.int64)
            a, b = pair // len(key), pair % len(key)
            a, b = np.where(key[a] <= key[b], a, b), np.where(key[a] <= key[b], b, a)
            out.append(pd.DataFrame({"gram": pd.array([pd.NA] * len(a), dtype="Int64"), "a": key[a], "b": key[b], "na": size[a], "nb": size[b], "shared": times, "short": True, "at": 0, "deal": 0}))
        many = np.flatnonzero((length > FEW) | hot)
        if len(many):
            at = np.repeat(begin[many] - np.concatenate(([0], np.cumsum(length[many])[:-1])), length[many]) + np.arange(length[many].sum())
            g, r = gram[at], row[at]
            nth = np.arange(len(at)) - np.repeat(np.cumsum(length[many]) - length[many], length[many])
            out.append(pd.DataFrame({"gram": pd.array(g.view(np.int64), dtype="Int64"), "a": key[r], "b": key[r], "na": size[r], "nb": size[r], "shared": 1, "short": short[at], "at": place[at], "deal": (part << 24) + nth // DEAL}))
        return pd.concat(out) if out else pd.DataFrame({c.split()[0]: pd.array([], dtype="boolean" if "bool" in c else "Int64") for c in HITS.split(", ")})

    return materialise(index.groupBy("part").applyInPandas(run, HITS), "hits")


def long_enough(na: Column, nb: Column) -> Column:
    return F.least(na, nb) * 4 >= F.greatest(na, nb) * 3


def overlap_needed(na: Column, nb: Column) -> Column:
    return F.ceil((na + nb) * 3 / F.lit(7.0) - F.lit(1e-9))


def shared_needed(na: Column, nb: Column) -> Column:
    """Prefix shingles two sets must share: their overlap less all that can lie behind the prefixes."""
    rest = lambda n: F.ceil(n * 3 / F.lit(4.0)) - 1
    return F.greatest(F.lit(1), overlap_needed(na, nb) - F.greatest(rest(na), rest(nb)))


def can_reach(na: Column, pa_: Column, nb: Column, pb: Column) -> Column:
    """Whether two sets that share a shingle at places pa_ and pb of the global order can overlap enough: by no more than
    the shorter part before it, the shingle, and the shorter part behind it."""
    return F.least(pa_, pb) + 1 + F.least(na - pa_ - 1, nb - pb - 1) >= overlap_needed(na, nb)


def enough(pairs: DataFrame, sieve: np.ndarray) -> DataFrame:
    """Pairs that may share enough: by their count alone, unless both are in the sieve of sets with star shingles."""
    shared = send(pairs.sparkSession, sieve)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b, na, nb, c = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(5))
            need = needed(na, nb) - np.maximum(-(-3 * na // 4), -(-3 * nb // 4)) + 1
            yield batch.filter(pa.array((c >= need) | (passes(shared.value, a) & passes(shared.value, b))))

    return pairs.mapInArrow(lean(run), "a long, b long, na long, nb long, shared long")


def verify(docs: DataFrame, pairs: DataFrame, shared) -> DataFrame:
    """The (a, b) of pairs of ids of which some sets reach the threshold; rows of one id may have different sets."""
    pairs = materialise(pairs.select("a", "b"), "pairs")
    hubs = pairs.groupBy("a").agg((F.ceil(F.count("*") / PARTNERS)).alias("deals"))
    dealt = pairs.join(hubs, "a").withColumn("deal", F.pmod(F.xxhash64("b"), "deals"))
    wanted = dealt.select("a", "deal", F.col("b").alias("doc_id")).unionByName(hubs.select("a", F.explode(F.sequence(F.lit(0), F.col("deals") - 1)).alias("deal"), F.col("a").alias("doc_id")))
    sieve = send(docs.sparkSession, sieve_of(wanted.select("doc_id").distinct()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in text_batches(batches):
            keys = batch.column(0).to_pylist()
            hit = [i for i, ok in enumerate(passes(sieve.value, np.array([k or 0 for k in keys], dtype=np.int64))) if ok and keys[i] is not None]
            sets = list(shingle_sets([texts[i] for i in hit], WORDS)) if hit else []
            prints = [hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets]
            yield pa.RecordBatch.from_arrays([pa.array([keys[i] for i in hit], pa.int64()), pa.array(prints, pa.binary()), pa.array([order(s, shared.value).tobytes() for s in sets], pa.binary())], ["doc_id", "print", "grams"])

    sets = docs.mapInArrow(lean(run), "doc_id long, print binary, grams binary").dropDuplicates(["doc_id", "print"]).drop("print")

    def join(frame: pd.DataFrame) -> pd.DataFrame:
        hub = frame["a"].iloc[0]
        members = [(k, np.frombuffer(g, dtype=np.uint64)) for k, g in zip(frame["doc_id"], frame["grams"])]
        others = Trie([m for m in members if m[0] != hub])
        got = sorted({k for own, probe in members if own == hub for k, _ in others.join(probe)})
        return pd.DataFrame({"a": [hub] * len(got), "b": got}, dtype="int64")

    out = materialise(wanted.join(sets, "doc_id").groupBy("a", "deal").applyInPandas(join, "a long, b long"), "links")
    sieve.unpersist()
    discard(pairs)
    return out


def link(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id of every row."""
    docs = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text"))
    spark = docs.sparkSession
    both = shingled(docs)
    sets = both.where("kind = 0").select("doc_id", "n", "print")
    shared = send(spark, count_table(both.where("kind = 1")))
    classes = materialise(sets.where("n > 0 AND doc_id IS NOT NULL").groupBy("print").agg(F.min("doc_id").alias("rep")), "classes")
    members = sets.where("doc_id IS NOT NULL").join(classes, "print", "left").select("doc_id", "n", F.coalesce("rep", "doc_id").alias("rep"))
    total = sets.agg(F.sum(F.col("n") / 4 + 1)).first()[0] or 0
    parts = max(1, int(total) // PART_SHINGLES + 1)
    hits = meet(prefix_index(docs, shared, parts), shared)
    reps = members.select("doc_id", "rep").distinct()
    # the classes of all texts of an id are one node
    several = reps.groupBy("doc_id").agg(F.min("rep").alias("a"), F.max("rep").alias("last")).where("a <> last").select("doc_id", "a")
    same = materialise(reps.join(several, "doc_id").where("a <> rep").select("a", F.col("rep").alias("b")), "same")

    def of_reps(pairs: DataFrame) -> DataFrame:
        there = pairs.join(reps.select(F.col("doc_id").alias("a"), F.col("rep").alias("ra")), "a").join(reps.select(F.col("doc_id").alias("b"), F.col("rep").alias("rb")), "b")
        return there.drop("a", "b").withColumnsRenamed({"ra": "a", "rb": "b"}).where("a <> b")

    # how many star shingles a set has in its prefix, which its pairs may share besides those counted
    held = materialise(hits.where("gram IS NOT NULL").groupBy(F.col("a").alias("doc_id")).agg(F.count("*").alias("held")), "held")
    paired = hits.where("gram IS NULL AND a <> b").groupBy("a", "b", "na", "nb").agg(F.sum("shared").alias("shared"))
    few = enough(paired, sieve_of(held.select("doc_id")))
    few = few.join(held.withColumnsRenamed({"doc_id": "a", "held": "ha"}), "a", "left").join(held.withColumnsRenamed({"doc_id": "b", "held": "hb"}), "b", "left")
    few = few.where(F.col("shared") + F.least(F.coalesce("ha", F.lit(0)), F.coalesce("hb", F.lit(0))) >= shared_needed(F.col("na"), F.col("nb")))
    few = of_reps(few).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), "shared").groupBy("a", "b").agg(F.max("shared").alias("shared"))
    # a star needs a member that has the shingle in its short prefix
    stars = hits.where("gram IS NOT NULL").select("gram", F.col("a").alias("doc_id"), F.col("na").alias("n"), "short", "at", "deal").join(reps, "doc_id")
    stars = stars.groupBy("gram", F.col("rep").alias("doc_id"), "n", "at").agg(F.max("short").alias("short"), F.min("deal").alias("deal"))
    live = hits.where("gram IS NOT NULL AND short").select("gram").distinct()
    deals = materialise(hits.where("gram IS NOT NULL").select("gram", "deal").distinct().join(live, "gram", "left_semi"), "deals")
    stars = materialise(stars.join(deals, ["gram", "deal"], "left_semi"), "stars")
    centres = materialise(stars.groupBy("gram").agg(F.min(F.struct("doc_id", "n", "at")).alias("c")).select("gram", F.col("c.doc_id").alias("centre"), F.col("c.n").alias("nc"), F.col("c.at").alias("pc")), "centres")
    rays = stars.join(centres.join(deals, "gram"), ["gram", "deal"]).where((F.col("doc_id") != F.col("centre")) & long_enough(F.col("n"), F.col("nc")) & can_reach(F.col("n"), F.col("at"), F.col("nc"), F.col("pc")))
    rays = rays.select(F.col("centre").alias("a"), F.col("doc_id").alias("b"))
    links = verify(docs, few.select("a", "b").unionByName(rays).distinct(), shared).unionByName(same)
    found = components(links)
    # members of a star outside its centre's component meet the others there
    placed = stars.join(found.withColumnRenamed("node", "doc_id"), "doc_id", "left").withColumn("component", F.coalesce("component", "doc_id"))
    main = centres.select("gram", F.col("centre").alias("node")).join(found, "node", "left").select("gram", F.coalesce("component", "node").alias("main"))
    away = placed.join(main.join(deals, "gram"), ["gram", "deal"]).where("component <> main")
    away = away.select("gram", F.col("doc_id").alias("a"), F.col("n").alias("na"), F.col("at").alias("pa"), F.col("short").alias("sa"), F.col("component").alias("ca")).join(deals, "gram")
    rest = placed.select("gram", "deal", F.col("doc_id").alias("b"), F.col("n").alias("nb"), F.col("at").alias("pb"), F.col("short").alias("sb"), F.col("component").alias("cb"))
    smaller_short = (F.col("sa") | (F.col("na") > F.col("nb"))) & (F.col("sb") | (F.col("nb") > F.col("na")))
    bounds = smaller_short & long_enough(F.col("na"), F.col("nb")) & can_reach(F.col("na"), F.col("pa"), F.col("nb"), F.col("pb"))
    again = away.join(rest, ["gram", "deal"]).where((F.col("ca") != F.col("cb")) & bounds)
    again = again.select(F.least("a", "b").alias("x"), F.greatest("a", "b").alias("y")).distinct()
    more = materialise(again.select(F.col("x").alias("a"), F.col("y").alias("b")), "again")
    if not more.isEmpty():
        found = components(links.unionByName(verify(docs, more, shared)))
    shared.unpersist()
    discard(hits, deals, stars, centres, held, more)
    named = members.join(found.withColumnRenamed("node", "rep"), "rep", "left").select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component", "rep").alias("component_id"))
    return named.unionByName(sets.where("doc_id IS NULL").select("doc_id", F.col("n").alias("n_shingles"), F.lit(None).cast("long").alias("component_id")))


def keep_first(docs: DataFrame) -> DataFrame:
    """The rows of docs, with all their columns, but one document of each component: that with the smallest doc_id. Of
    rows with words that repeat its id one stays, that with the first text. Documents without words or id stay."""
    linked = link(docs)
    gone = materialise(linked.where("doc_id <> component_id").select("doc_id").distinct(), "gone")
    kept = docs.join(gone, docs["doc_id"] == gone["doc_id"], "left_anti")
    again = materialise(linked.where("doc_id = component_id AND n_shingles > 0").groupBy("doc_id").count().where("count > 1").select(F.col("doc_id").alias("_again")), "again")
    if again.isEmpty():
        return kept
    worded = F.coalesce(F.col("text").rlike(r"[^\x20\x09-\x0D]"), F.lit(False))
    more = kept.where(worded).join(again, F.col("doc_id") == F.col("_again"), "left_semi")
    once = more.groupBy(F.col("doc_id").alias("_key")).agg(F.min_by(F.struct(*[F.col(f"`{c}`") for c in docs.columns]), "text").alias("_row")).select("_row.*")
    rest = kept.where(worded).join(again, F.col("doc_id") == F.col("_again"), "left_anti")
    return rest.unionByName(kept.where(~worded)).unionByName(once)


ORACLE: str = r"""
    WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
    s AS (SELECT DISTINCT doc_id, array_to_string(w[i : i + 4], ' ') AS g FROM d, unnest(range(1, greatest(2, len(w) - 3))) AS u(i) WHERE len(w) > 0),
    n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
    c AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS o FROM s x JOIN s y ON x.g = y.g AND x.doc_id <> y.doc_id GROUP BY 1, 2),
    e AS (SELECT a, b FROM c JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * o >= 75 * (na.n + nb.n - o)),
    walk AS (SELECT doc_id AS a, doc_id AS b FROM d UNION SELECT walk.a, e.b FROM walk JOIN e ON walk.b = e.a)
    SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, t.component_id FROM d LEFT JOIN n USING (doc_id) JOIN (SELECT a AS doc_id, min(b) AS component_id FROM walk GROUP BY a) t USING (doc_id)"""
