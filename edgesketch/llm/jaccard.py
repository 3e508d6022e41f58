"""N-gram Jaccard join in metric space: pivots, Voronoi regions, triangle-inequality windows.

A document's set are the hashes of its distinct word shingles; equal sets are one class, told by a
127-bit hash, and only classes are joined. The Jaccard distance d is a metric, so with a radius r:

1. *Singleton pivots.* Each shingle is a pivot with the set of it alone; a class ranks them by
   nearness, ties by how rare they are, and is put to its first ``n - ceil(t n) + 1``. Two classes
   within r share one of those, so no link is lost between the regions of these pivots. How often
   shingles occur is gathered over all documents by lossy counting and orders the ties only.
2. *Bin pivots.* In the region of a rare shingle, pairs are tested against pivots that are the bins
   of the hash space, 64 or more for large sets: by the triangle inequality of the symmetric difference, the sum of |a_g - b_g|
   over the bins g never exceeds |A xor B|. In the region of a frequent shingle no pairs are made;
   a class is tied once to each group of those before it that the bins don't part from it. Only the
   classes of a hub, a shingle of thousands of them, are tied to one centre unseen.
3. What is tied together by 2 is a region. Its sets are fetched once, and the region is joined
   exactly and recursively, whatever its size: some members become pivots and are joined with all, any
   other class goes to its nearest pivot's Voronoi cell, and to that of any other pivot q with
   (d(x, q) - d(x, p)) / 2 <= r, and cells are joined alike.
   A region too large for a task is split the same way between tasks first; what a turn does not
   shrink is joined in pairs of blocks at once, without a copy for each cell.

Links found are checked on the full sets in whole numbers: 100 * |A and B| >= percent * |A or B|.

Defined results: null, empty and word-less texts have an empty set and link with nothing; a text of
fewer words than a shingle is one shingle of all of them; equal texts link; repeated rows get a row
each; an empty table gives no rows; extra columns are ignored by ``classes`` and pass through
``keep_one``; very long texts are taken whole.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgesketch.llm import textkit as K
from edgesketch.llm.common import Sieve, materialize, partitions_for, scratch_scope, table, text_slices
from edgesketch.llm.components import connected

BINS = 64


def bins_for(n: int) -> int:
    """Bins of a set of n: a power of two, about one for each 16 shingles, so that strangers differ."""
    return max(BINS, 1 << max(0, (n // 16 - 1).bit_length()))


#: A shingle in more classes is frequent: its region is tied together instead of paired.
FREQUENT = 32
#: A shingle in more classes is a hub: its region is tied to a centre.
HUB = 2048
#: A shingle in so many documents is ranked behind rarer ones.
RANKED = 6
#: Most entries of the ranking table that is broadcast; what is beyond it is only ranked as rare.
RANKING_ENTRIES = 1 << 20
#: Classes and shingles of a region that one task joins.
REGION_CLASSES, REGION_SHINGLES = 20_000, 6_000_000
#: Most pivots of a region.
PIVOTS = 8
#: Bytes of sets that come to the driver as pivots of large regions.
PIVOT_BYTES = 64 << 20


def shingle_sets(column, width: int) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text."""
    data, offsets = K.raw(column)
    data = K.FOLDED[data]
    starts, ends, first = K.words(data, offsets, K.NOT_SPACE)
    hashes = K.span_hash(K.prefix_sums(data), starts, ends)
    windows = K.window_hash(hashes, width)
    out = []
    for a, b in zip(first[:-1].tolist(), first[1:].tolist()):
        if b - a >= width:
            out.append(np.unique(windows[a : b - width + 1]))
        elif b > a:
            out.append(K.window_hash(hashes[a:b], b - a) ^ np.uint64(b - a))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def class_id(own: np.ndarray) -> tuple[int, int]:
    """A class's id: 63 and 64 bits of a cryptographic hash of its set, so ids don't depend on doc_ids."""
    told = hashlib.blake2b(own.tobytes(), digest_size=16).digest()
    return int.from_bytes(told[:8], "little") >> 1, int.from_bytes(told[8:], "little", signed=True)


#: Most ids of 63 bits that two classes may share; 10**10 documents expect about five.
MOST_SHARED = 100_000


def told_apart(wide: DataFrame) -> tuple[DataFrame, dict[tuple[int, int], int]]:
    """Classes that share their first 63 bits get an id of all 127; (documents, the ids of those classes)."""
    by = wide.where("n > 0").groupBy("cid").agg(F.min("cid2").alias("lo"), F.max("cid2").alias("hi"))
    shared = [r.cid for r in by.where("lo <> hi").select("cid").limit(MOST_SHARED + 1).toLocalIterator()]
    if len(shared) > MOST_SHARED:
        raise RuntimeError("too many classes share an id")
    if not shared:
        return wide, {}
    joint = F.xxhash64("cid", "cid2").bitwiseAND(F.lit((1 << 63) - 1))
    parted = F.broadcast(wide.sparkSession.createDataFrame(pa.table({"cid": shared})).withColumn("parted", F.lit(True)))
    marked = wide.join(parted, "cid", "left").withColumn("joint", F.when(F.col("parted"), joint).otherwise(F.col("cid")))
    names = {(r.cid, r.cid2): r.joint for r in marked.where("parted and n > 0").select("cid", "cid2", "joint").distinct().toLocalIterator()}
    return materialize(marked.withColumn("cid", F.col("joint")).select(*wide.columns), "told-apart"), names


def prefix_length(n: int, percent: int) -> int:
    return n + (-percent * n // 100) + 1


def _row():
    """A hash of a row's doc_id and text: rows may share a doc_id, or have none."""
    return F.xxhash64(F.col("doc_id").cast("long"), F.col("text").cast("string"))


def _docs(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), _row().alias("row"), F.col("text").cast("string").alias("text"))


def _least(row: str, doc_id: str):
    """The row of least doc_id; the least row where all doc_ids are null."""
    return F.coalesce(F.min_by(row, doc_id), F.min(row))


def ranking(docs: DataFrame, width: int, seen: int = RANKED, entries: int = RANKING_ENTRIES) -> tuple[np.ndarray, np.ndarray]:
    """Frequent shingles with their counts, by lossy counting over all documents: (hashes, counts)."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0

        def told():
            u, c = np.unique(np.concatenate(held), return_counts=True)
            keep = c > 1
            return pa.RecordBatch.from_arrays([pa.array(u[keep].view(np.int64)), pa.array(c[keep].astype(np.int64))], names=["h", "n"])

        for whole in batches:
            for batch in text_slices(whole, "text"):
                held += shingle_sets(batch.column("text"), width)
                size += sum(map(len, held[-batch.num_rows :]))
                if size > 4_000_000:
                    yield told()
                    held, size = [], 0
        if held:
            yield told()

    counted = _docs(docs).mapInArrow(count, "h long, n long").groupBy("h").agg(F.sum("n").alias("n")).where(F.col("n") >= seen)
    top = counted.orderBy(F.desc("n"), "h").limit(entries).toArrow()  # bounded by ``entries``
    h, n = (top[k].to_numpy().astype(np.int64) for k in ("h", "n"))
    h = h.view(np.uint64)
    order = np.argsort(h)
    return h[order], n[order]


WIDE = "doc_id long, row long, n long, cid long, cid2 long, prefix binary, bins binary"


def prefixes(docs: DataFrame, width: int, percent: int, ranked) -> DataFrame:
    """Each document with its set size, class, first singleton pivots and bin counts."""

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, counts = ranked.value
        for whole in batches:
            for batch in text_slices(whole, "text"):
                sets = shingle_sets(batch.column("text"), width)
                prefix, bins = [], []
                for own in sets:
                    n = len(own)
                    rank = own
                    if n and len(known):
                        at = np.minimum(np.searchsorted(known, own), len(known) - 1)
                        often = np.where(known[at] == own, counts[at], 0)
                        if often.any():
                            rank = own[np.lexsort((own, often))]
                    prefix.append(rank[: prefix_length(n, percent)].tobytes() if n else None)
                    b = bins_for(n)
                    top = (own >> np.uint64(65 - b.bit_length())).astype(np.int64)
                    bins.append(np.minimum(np.bincount(top, minlength=b), 65535).astype("<u2").tobytes())
                ids = np.array([class_id(s) for s in sets], np.int64).reshape(-1, 2)
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id"), batch.column("row"), pa.array([len(s) for s in sets], pa.int64()), pa.array(ids[:, 0]), pa.array(ids[:, 1]), pa.array(prefix, pa.binary()), pa.array(bins, pa.binary())],
                    names=["doc_id", "row", "n", "cid", "cid2", "prefix", "bins"],
                )

    return _docs(docs).mapInArrow(look, WIDE)


def _spread(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row for each class and singleton pivot."""
    for batch in rows:
        bodies = batch.column("prefix").to_pylist()
        each = np.array([len(b) // 8 for b in bodies], np.int64)
        for at in range(0, len(bodies), 2000):
            part = slice(at, at + 2000)
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.frombuffer(b"".join(bodies[part]), np.int64)), pa.array(np.repeat(batch.column("cid").to_numpy()[part], each[part])), pa.array(np.repeat(batch.column("n").to_numpy()[part], each[part]).astype(np.int32))],
                names=["h", "cid", "n"],
            )


#: What a row of ``_pairs_of_runs`` tells: a pair to test, a tie, or a member (b) of a run (a).
TIE, PAIR, MEMBER = 0, 1, 2


def _pairs_of_runs(percent: int, frequent: int, hub: int = HUB):
    """Over rows sorted by (h, n): PAIRs within runs of a shingle by size, MEMBERs of longer runs, or TIEs to a hub's head."""

    def look(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest = None
        centre: tuple[int, int] | None = None  # (h, cid) of a hub's run that has been cut

        def work(h, cid, n, last: bool):
            nonlocal rest, centre
            edge = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1], [True]]))
            starts, sizes = edge[:-1], np.diff(edge)
            if not last:
                stop = int(starts[-1])
                if sizes[-1] <= hub:
                    rest = (h[stop:], cid[stop:], n[stop:])
                    starts, sizes = starts[:-1], sizes[:-1]
                else:
                    rest = None
            a, b, kind = [], [], []
            some = sizes > 1
            for s, k in zip(starts[some].tolist(), sizes[some].tolist()):
                if centre is not None and centre[0] == h[s] or k > hub:
                    head = centre[1] if centre is not None and centre[0] == h[s] else int(cid[s])
                    a.append(np.full(k, head))
                    b.append(cid[s : s + k])
                    kind.append(np.full(k, TIE, np.int32))
                    centre = (int(h[s]), head)
                elif k > frequent:
                    # named by its members: the shingles of a passage have mostly the same ones
                    name = hashlib.blake2b(cid[s : s + k].tobytes(), digest_size=8).digest()
                    a.append(np.full(k, int.from_bytes(name, "little", signed=True)))
                    b.append(cid[s : s + k])
                    kind.append(np.full(k, MEMBER, np.int32))
                else:
                    i, j = np.triu_indices(k, 1)  # at most ``frequent`` rows
                    fit = 100 * n[s + i].astype(np.int64) >= percent * n[s + j].astype(np.int64)
                    a.append(cid[s + i[fit]])
                    b.append(cid[s + j[fit]])
                    kind.append(np.full(int(fit.sum()), PAIR, np.int32))
            if centre is not None and len(starts) and sizes[0] == 1 and centre[0] == h[0]:
                a.append(np.array([centre[1]]))
                b.append(cid[:1])
                kind.append(np.full(1, TIE, np.int32))
            if a:
                a, b, kind = np.concatenate(a), np.concatenate(b), np.concatenate(kind)
                lo, hi = (np.where(kind == MEMBER, x, least(a, b)) for x, least in ((a, np.minimum), (b, np.maximum)))
                _, keep = np.unique(np.stack([lo, hi, kind.astype(np.int64)]), axis=1, return_index=True)
                keep = keep[(lo[keep] != hi[keep]) | (kind[keep] == MEMBER)]
                return pa.RecordBatch.from_arrays([pa.array(lo[keep]), pa.array(hi[keep]), pa.array(kind[keep])], names=["a", "b", "kind"])
            return None

        for batch in rows:
            h, cid, n = (batch.column(k).to_numpy() for k in ("h", "cid", "n"))
            if rest is not None:
                h, cid, n = (np.concatenate([x, y]) for x, y in zip(rest, (h, cid, n)))
                rest = None
            if len(h) and (out := work(h, cid, n, False)) is not None:
                yield out
        if rest is not None and len(rest[0]) and (out := work(*rest, True)) is not None:
            yield out

    return look


#: Most bins that are told apart in a long run: wider ones are added up to so many.
RUN_BINS = 1024


def run_ties(n: np.ndarray, bins: list[np.ndarray], percent: int) -> list[tuple[int, int]]:
    """Ties between classes in order of size n: whatever may link is tied or tied already, and strangers are not tied themselves."""
    size = np.array([len(b) for b in bins])
    full = np.array([bool((b == 65535).any()) for b in bins])  # such a bin says nothing
    own = [b.astype(np.int64).reshape(min(len(b), RUN_BINS), -1).sum(axis=1) for b in bins]
    edge = np.flatnonzero(np.concatenate([[True], np.minimum(size[1:], RUN_BINS) != np.minimum(size[:-1], RUN_BINS), [True]])).tolist()
    levels = [(x, y, np.stack(own[x:y])) for x, y in zip(edge, edge[1:])]
    comp, ties = np.arange(len(n)), []
    for i in range(1, len(n)):
        first, stop, width = int(np.searchsorted(100 * n[:i], percent * n[i])), i, 32
        while stop > first:
            start, width = max(first, stop - width), 2 * width
            for x, y, body in levels:
                some = np.arange(max(x, start), min(y, stop))
                some = some[comp[some] != comp[i]]
                if len(some):
                    apart = np.abs(body[some - x] - own[i].reshape(body.shape[1], -1).sum(axis=1)).sum(axis=1)
                    near = full[i] | full[some] | (apart * (100 + percent) <= (100 - percent) * (n[some] + n[i]))
                    for j in some[near].tolist():
                        if comp[j] != comp[i]:
                            ties.append((j, i))
                            comp[comp == comp[j]] = comp[i]
            stop = start
    return ties


def _ties_of_runs(percent: int):
    """Over rows sorted by (run, n): ``run_ties`` of each run, at most one less than its members."""

    def look(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []

        def told():
            cid, n = (np.array([x[k] for x in held], np.int64) for k in (0, 1))
            ties = run_ties(n, [np.frombuffer(x[2], "<u2") for x in held], percent) if len(held) > 1 else []
            return pa.RecordBatch.from_arrays([pa.array(cid[[t[k] for t in ties]] if ties else [], pa.int64()) for k in (0, 1)], names=["a", "b"])

        for batch in rows:
            for run, *member in zip(*(batch.column(k).to_pylist() for k in ("run", "cid", "n", "bins"))):
                if run != now:
                    yield told()
                    now, held = run, []
                held.append(member)
        yield told()

    return look


def pivot_rows(wide: DataFrame, hot, hub: int = HUB) -> tuple[DataFrame, DataFrame]:
    """(a row for each class and singleton pivot, the bins of each class); both outlive the caller's scope, what they are made of doesn't."""
    spark = wide.sparkSession
    classes = wide.where("n > 0").groupBy("cid").agg(F.first(F.struct("n", "prefix", "bins")).alias("x")).select("cid", "x.*")
    classes = materialize(classes, "classes")
    rows = classes.select("cid", "n", "prefix").mapInArrow(_spread, "h long, cid long, n int")
    known, counts = hot
    often = spark.createDataFrame(pa.table({"h": known[counts >= hub].view(np.int64)}))
    marked = rows.join(F.broadcast(often.withColumn("hot", F.lit(True))), "h", "left")
    return materialize(marked, "pivots", outer=1), materialize(classes.select("cid", "n", "bins"), "bins", outer=1)


def candidate_links(wide: DataFrame, percent: int, frequent: int, hot, hub: int = HUB) -> DataFrame:
    """(a, b) class links whose components are the regions: 2 of the module's text."""
    with scratch_scope(wide.sparkSession):
        marked, bins = pivot_rows(wide, hot, hub)
    return links_of_pivots(marked, bins, percent, frequent, hub)


def links_of_pivots(marked: DataFrame, bins: DataFrame, percent: int, frequent: int, hub: int = HUB) -> DataFrame:
    """``candidate_links`` of classes whose pivots are written already."""
    spark = marked.sparkSession
    # hubs: a centre for each by partial aggregates, then ties to it
    heads = marked.where("hot").groupBy("h").agg(F.min("cid").alias("a"))
    ties = marked.where("hot").join(F.broadcast(heads), "h").select("a", F.col("cid").alias("b")).where("a <> b").distinct()
    # others: pairs within the region of a rare shingle, the members of that of a frequent one
    cold = marked.where("hot is null").drop("hot").repartition(partitions_for(spark), "h").sortWithinPartitions("h", "n", "cid")
    found = materialize(cold.mapInArrow(_pairs_of_runs(percent, frequent, hub), "a long, b long, kind int").distinct(), "candidates")
    # of the bins only those of classes that are in a pair or a run are shuffled
    met = found.where(F.col("kind") != TIE).select(F.explode(F.when(F.col("kind") == PAIR, F.array("a", "b")).otherwise(F.array("b"))).alias("cid"))
    bins = Sieve(met, "cid").may_have(bins, "cid")
    left = bins.toDF("a", "na", "ba")
    right = bins.toDF("b", "nb", "bb")

    def near(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            both = batch.column("na").to_numpy() + batch.column("nb").to_numpy()
            x, y = batch.column("ba").to_pylist(), batch.column("bb").to_pylist()
            keep = np.zeros(batch.num_rows, bool)
            kinds: dict[tuple[int, int], list[int]] = {}
            for k, (u, v) in enumerate(zip(x, y)):
                kinds.setdefault((len(u), len(v)), []).append(k)
            for (lu, lv), some in kinds.items():
                b = min(lu, lv) // 2
                u, v = (np.frombuffer(b"".join(z[k] for k in some), "<u2").reshape(len(some), b, -1) for z in (x, y))
                full = (u.max(axis=(1, 2)) == 65535) | (v.max(axis=(1, 2)) == 65535)  # such a bin says nothing
                apart = np.abs(u.sum(axis=2, dtype=np.int64) - v.sum(axis=2, dtype=np.int64)).sum(axis=1)
                # |A xor B| <= (1 - t) / (1 + t) * (|A| + |B|)
                keep[some] = full | (apart * (100 + percent) <= (100 - percent) * both[some])
            yield batch.select(["a", "b"]).filter(pa.array(keep))

    passed = found.where(F.col("kind") == PAIR).join(left, "a").join(right, "b").select("a", "b", "na", "nb", "ba", "bb").mapInArrow(near, "a long, b long")
    runs = found.where(F.col("kind") == MEMBER).select(F.col("a").alias("run"), F.col("b").alias("cid")).join(bins, "cid")
    runs = runs.repartition(partitions_for(spark), "run").sortWithinPartitions("run", "n", "cid").select("run", "cid", "n", "bins")
    parted = runs.mapInArrow(_ties_of_runs(percent), "a long, b long")
    return passed.union(parted).union(found.where(F.col("kind") == TIE).select("a", "b")).union(ties)


class Region:
    """An exact join of the sets of a region; only links that tie two components are told."""

    def __init__(self, ids: np.ndarray, sets: list[np.ndarray], percent: int):
        self.ids, self.percent, self.radius = ids, percent, 1 - percent / 100 + 1e-9
        self.n = np.array([len(s) for s in sets], np.int64)
        _, flat = np.unique(np.concatenate(sets), return_inverse=True)
        self.at = np.concatenate([[0], np.cumsum(self.n)])
        self.flat = flat
        self.top = int(flat.max()) + 1
        self.mark = np.zeros(self.top, bool)
        self.comp = np.arange(len(sets))
        self.links: list[tuple[int, int]] = []
        #: Pivots taken, Voronoi cells joined, members that windows put into further cells, and members joined without pivots.
        self.pivots = self.cells = self.windowed = self.flat_members = 0

    def own(self, k: int) -> np.ndarray:
        return self.flat[self.at[k] : self.at[k + 1]]

    def shared(self, k: int, others: np.ndarray) -> np.ndarray:
        """|A and B| of member k with each of the others."""
        self.mark[self.own(k)] = True
        n = self.n[others]
        ends = np.cumsum(n)
        index = np.arange(ends[-1]) + np.repeat(self.at[others] - (ends - n), n)
        out = np.add.reduceat(self.mark[self.flat[index]], ends - n, dtype=np.int64)
        self.mark[self.own(k)] = False
        return out

    def join(self, k: int, others: np.ndarray) -> np.ndarray:
        """Links k with those of the others that are near enough; the distances."""
        both = self.shared(k, others)
        either = self.n[k] + self.n[others] - both
        for o in others[100 * both >= self.percent * either].tolist():
            if self.comp[o] != self.comp[k]:
                self.links.append((int(self.ids[k]), int(self.ids[o])))
                self.comp[self.comp == self.comp[o]] = self.comp[k]
        return 1 - both / either

    def solve(self, members: np.ndarray, depth: int = 0) -> None:
        """Some members become pivots; they are joined with all, and the rest cell by cell."""
        if len(members) < 2 or (self.comp[members] == self.comp[members[0]]).all():
            return
        if len(members) == 2:
            self.join(int(members[0]), members[1:])
            return
        if depth > 12:
            return self.leaf(members)
        count = min(PIVOTS, max(2, int(len(members) ** 0.5)))
        spots = np.unique(np.linspace(0, len(members) - 1, count).astype(np.int64))
        d = np.stack([self.join(int(p), members) for p in members[spots]])
        home = d.argmin(axis=0)
        nearest = d[home, np.arange(len(members))]
        rest = np.ones(len(members), bool)
        rest[spots] = False  # the pivots' links are known
        inside = [((home == k) | ((d[k] - nearest) / 2 <= self.radius)) & rest for k in range(len(spots))]
        cells = [members[i] for k, i in enumerate(inside) if (home[rest] == k).any()]
        self.pivots += len(spots)
        if len(members) > 24 and cells and (sum(map(len, cells)) > 2 * len(members) or max(map(len, cells)) > 0.9 * len(members)):
            return self.leaf(members[rest])  # the pivots do not part these members
        self.cells += len(cells)
        self.windowed += sum(map(len, cells)) - int(rest.sum())
        for cell in cells:
            self.solve(cell, depth + 1)

    def leaf(self, members: np.ndarray) -> None:
        """By rising size, against earlier members that share one of the first shingles, rarest here first."""
        self.flat_members += len(members)
        members = members[np.argsort(self.n[members], kind="stable")]
        often = np.bincount(np.concatenate([self.own(int(k)) for k in members]), minlength=self.top)
        lists: dict[int, list[int]] = {}
        for k in members.tolist():
            own = self.own(k)
            first = own[np.lexsort((own, often[own]))][: prefix_length(int(self.n[k]), self.percent)].tolist()
            met = set().union(*(lists.get(x, ()) for x in first))
            if met:
                others = np.fromiter(met, np.int64, len(met))
                others = others[(self.comp[others] != self.comp[k]) & (100 * self.n[others] >= self.percent * self.n[k])]
                if len(others):
                    self.join(k, np.sort(others))
            for x in first:
                lists.setdefault(x, []).append(k)


SETS = "region long, cid long, body binary"


def _region_sets(docs: DataFrame, wide: DataFrame, regions: DataFrame, width: int, shared: dict[tuple[int, int], int] | None = None) -> DataFrame:
    """The set of each class of a region, made anew from the text of one of its rows."""
    one = wide.join(regions, "cid").groupBy("cid", "region").agg(_least("row", "doc_id").alias("row"))
    one = materialize(one, "region-rows")
    met = Sieve(one, "row").may_have(_docs(docs), "row").join(one, "row").select("region", "cid", "text")  # of the texts only those of regions are shuffled

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()  # rows that are repeated give a class once a task
        for whole in batches:
            for batch in text_slices(whole, "text"):
                sets = shingle_sets(batch.column("text"), width)
                ids = [(shared or {}).get(i, i[0]) for i in map(class_id, sets)]
                same = pa.array([c not in seen and i == c and not seen.add(c) for i, c in zip(ids, batch.column("cid").to_pylist())], pa.bool_())
                yield pa.RecordBatch.from_arrays([batch.column("region"), batch.column("cid"), pa.array([s.tobytes() for s in sets], pa.binary())], names=["region", "cid", "body"]).filter(same)

    return met.mapInArrow(look, SETS)


def _solve_sorted(percent: int):
    """Joins each region of rows that are sorted by region."""

    def look(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, {}

        def told():
            if len(held) > 1:
                ids = np.array(sorted(held), np.int64)
                region = Region(ids, [np.frombuffer(held[i], np.uint64) for i in ids.tolist()], percent)
                region.solve(np.arange(len(ids)))
                if region.links:
                    return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*region.links)], names=["a", "b"])
            return None

        for batch in rows:
            for region, cid, body in zip(batch.column("region").to_pylist(), batch.column("cid").to_pylist(), batch.column("body").to_pylist()):
                if region != now:
                    if (out := told()) is not None:
                        yield out
                    now, held = region, {}
                held[cid] = body
        if (out := told()) is not None:
            yield out

    return look


def _in_pairs_of_blocks(many: DataFrame, most_classes: int, most_shingles: int) -> DataFrame:
    """The sets of regions of k classes and s shingles, so that any two of a region meet in a region of a bounded size."""
    parts = F.ceil(F.greatest(F.col("k") / F.lit(most_classes / 2), F.col("s") / F.lit(most_shingles / 2))).cast("long")
    block = F.pmod(F.xxhash64("cid"), parts)
    with_each = F.transform(F.sequence(F.lit(0).cast("long"), parts - 1), lambda o: F.struct(F.least(block, o).alias("i"), F.greatest(block, o).alias("j")))
    dealt = many.select(F.explode(with_each).alias("ij"), "region", "cid", "body")
    return dealt.select(F.xxhash64("region", "ij.i", "ij.j").alias("region"), "cid", "body")


def _pivots(many: DataFrame, turn: int, most_bytes: int = PIVOT_BYTES) -> dict[int, list]:
    """Some sets of each region, at most 4096 and at most ``most_bytes`` of all regions."""
    chance = F.lit(4.0 * PIVOTS) / F.col("k")
    drawn = many.where(F.pmod(F.xxhash64("cid", F.lit(turn)), F.lit(1 << 30)) < chance * (1 << 30)).select("region", "cid", "body")
    largest = drawn.agg(F.max(F.octet_length("body")).alias("n")).first().n
    out: dict[int, list] = {}
    for r in drawn.limit(min(4096, most_bytes // largest) if largest else 0).toLocalIterator():
        out.setdefault(r.region, []).append((r.cid, np.frombuffer(bytes(r.body), np.uint64)))
    return out


CELLS = "region long, cid long, body binary, k long, s double, cells array<long>, links array<long>"


def _part_large(sets: DataFrame, percent: int, most_classes: int, most_shingles: int, rounds: int = 6) -> tuple[DataFrame, DataFrame | None]:
    """Splits regions that are too large for a task by pivots, between tasks; (sets, links found by it).

    A region that a turn does not split well (its largest cell keeps over 0.9 of the classes, or all
    cells together over twice of them) is joined in pairs of blocks at once, and so is what is left
    after ``rounds``, or once the rows are over four times those of the first turn. No copy is
    written before that is known.
    """
    spark, links, settled, first = sets.sparkSession, None, None, None
    radius = 1 - percent / 100 + 1e-9
    for turn in range(rounds + 1):
        size = sets.groupBy("region").agg(F.count(F.lit(1)).alias("k"), F.sum(F.octet_length("body") / 8).alias("s"))
        large = materialize(size.where((F.col("k") > most_classes) | (F.col("s") > most_shingles)), "large")
        rows = large.agg(F.sum("k").alias("k")).first().k
        small = sets.join(F.broadcast(large.select("region")), "region", "left_anti") if rows else sets
        settled = small if settled is None else settled.unionByName(small)
        if not rows:
            return settled, links
        first = first or rows
        many = sets.join(F.broadcast(large), "region").select("region", "cid", "body", "k", "s")
        pivots = _pivots(many, turn) if turn < rounds and rows <= 4 * first else {}
        if not pivots:
            return settled.unionByName(materialize(_in_pairs_of_blocks(many, most_classes, most_shingles), "blocks")), links
        told = spark.sparkContext.broadcast(pivots)

        def part(rows, told=told, turn=turn):
            for batch in (b.slice(i, 256) for b in rows for i in range(0, b.num_rows, 256)):
                cells, links = [], []
                for region, cid, body in zip(*(batch.column(x).to_pylist() for x in ("region", "cid", "body"))):
                    own, a = told.value.get(region), np.frombuffer(body, np.uint64)
                    cells.append([] if own else [region])
                    links.append([])
                    d = []
                    for other, b in own or ():
                        both = len(np.intersect1d(a, b, assume_unique=True))
                        either = len(a) + len(b) - both
                        d.append(1 - both / either)
                        if 100 * both >= percent * either and other != cid:
                            links[-1].append(other)
                    near = min(d, default=0)
                    for x, (other, _) in zip(d, own or ()):
                        if x == near or (x - near) / 2 <= radius:
                            cell = hashlib.blake2b(f"{region} {other} {turn}".encode(), digest_size=8).digest()
                            cells[-1].append(int.from_bytes(cell, "little", signed=True))
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(cells, pa.list_(pa.int64())), pa.array(links, pa.list_(pa.int64()))], names=[*batch.schema.names, "cells", "links"])

        done = materialize(many.mapInArrow(part, CELLS), "cells")
        more = done.select(F.col("cid").alias("a"), F.explode("links").alias("b"))
        links = more if links is None else links.union(more)
        cell = done.select("region", "k", F.explode("cells").alias("cell")).groupBy("region", "k", "cell").agg(F.count(F.lit(1)).alias("n"))
        whole = cell.groupBy("region", "k").agg(F.sum("n").alias("n"), F.max("n").alias("top"))
        stuck = materialize(whole.where((F.col("n") > 2 * F.col("k")) | (F.col("top") > 0.9 * F.col("k"))).select("region"), "stuck")
        pairs = _in_pairs_of_blocks(done.join(F.broadcast(stuck), "region", "left_semi"), most_classes, most_shingles)
        settled = settled.unionByName(materialize(pairs, "blocks"))
        sets = materialize(done.join(F.broadcast(stuck), "region", "left_anti").select(F.explode("cells").alias("region"), "cid", "body"), "parted")


def _grouped(docs: DataFrame, width: int, percent: int, frequent: int = FREQUENT, most_classes: int = REGION_CLASSES, most_shingles: int = REGION_SHINGLES) -> DataFrame:
    """doc_id, row and set size of every row, and of its component the least doc_id and the row that has it."""
    spark = docs.sparkSession
    hot = ranking(docs, width)
    with scratch_scope(spark):
        with scratch_scope(spark):  # the packed pivots go before their rows are dealt by shingle
            packed, shared = told_apart(materialize(prefixes(docs, width, percent, spark.sparkContext.broadcast(hot)), "sets"))
            wide = materialize(packed.select("doc_id", "row", "n", "cid"), "rows", outer=2)
            marked, bins = pivot_rows(packed, hot)
        regions = connected(links_of_pivots(marked, bins, percent, frequent)).toDF("cid", "region")
        regions = materialize(regions, "region-names", outer=True)
    with scratch_scope(spark):
        sets = materialize(_region_sets(docs, wide.select("doc_id", "row", "cid"), regions, width, shared), "regions")
        sets, found = _part_large(sets, percent, most_classes, most_shingles)
        dealt = sets.repartition(partitions_for(spark), "region").sortWithinPartitions("region")
        links = dealt.mapInArrow(_solve_sorted(percent), "a long, b long")
        links = materialize(links if found is None else links.union(found), "found-links", outer=True)
    roots = connected(links)
    least = wide.where("n > 0").groupBy("cid").agg(F.min("doc_id").alias("least"), _least("row", "doc_id").alias("least_row"))
    named = least.join(roots.toDF("cid", "root"), "cid", "left").select("cid", "least", "least_row", F.coalesce("root", "cid").alias("root"))
    component = named.groupBy("root").agg(F.min("least").alias("component_id"), _least("least_row", "least").alias("first_row"))
    by_class = named.join(component, "root").select("cid", "component_id", "first_row")
    return wide.select("doc_id", "row", "n", F.when(F.col("n") > 0, F.col("cid")).alias("cid")).join(by_class, "cid", "left")


def classes(docs: DataFrame, width: int = 5, percent: int = 80, frequent: int = FREQUENT, most_classes: int = REGION_CLASSES, most_shingles: int = REGION_SHINGLES) -> DataFrame:
    """doc_id, n_shingles and component_id (the least doc_id reachable by links) of every document."""
    out = _grouped(docs, width, percent, frequent, most_classes, most_shingles)
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"))


def keep_one(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """The documents without near-duplicates: of each group of links one row of the least doc_id stays.

    Rows are told apart by doc_id and text, so a null or repeated doc_id alone drops nothing; of rows
    that are equal in both, one stays.
    """
    with scratch_scope(docs.sparkSession):
        found = _grouped(docs, width, percent).select("doc_id", "row", (F.col("row") != F.col("first_row")).alias("lost"))
        found = materialize(found, "near-duplicates", outer=True)
    lost = materialize(found.where("lost").select(F.col("doc_id").alias("__es_id"), F.col("row").alias("__es_lost")).distinct(), "lost-rows")
    twice = found.groupBy("doc_id", "row").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    twice = materialize(twice.select(F.col("doc_id").alias("__es_id"), F.col("row").alias("__es_lost")), "repeated-rows")
    met = F.col("doc_id").cast("long").eqNullSafe(F.col("__es_id")) & (F.col("__es_row") == F.col("__es_lost"))
    named = docs.withColumn("__es_row", _row())
    # of the texts only those of rows that may be lost or repeated are shuffled
    sieve = Sieve(lost.union(twice), "__es_lost")
    kept = sieve.may_have(named, "__es_row").join(lost, met, "left_anti")
    if not twice.isEmpty():
        once = kept.join(twice, met, "left_anti")
        kept = once.unionByName(kept.join(twice, met, "left_semi").dropDuplicates(["doc_id", "__es_row"]))
    kept = sieve.surely_without(named, "__es_row").unionByName(kept)
    return kept.drop("__es_row")


def query(spark, sf_dir: str) -> DataFrame:
    return classes(table(spark, sf_dir, "documents"), width=4, percent=85)


ORACLE = r"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
i AS (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 4, 0) + 2)) AS k FROM d WHERE len(w) > 0),
s AS MATERIALIZED (SELECT DISTINCT doc_id, array_to_string(w[k:k + 3], ' ') AS g FROM i),
n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
o AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS MATERIALIZED (SELECT x, y FROM o JOIN n p ON p.doc_id = x JOIN n q ON q.doc_id = y WHERE 100 * c >= 85 * (p.n + q.n - c)),
e AS MATERIALIZED (SELECT x, y FROM l UNION SELECT y, x FROM l),
r(doc_id, root) AS (SELECT doc_id, doc_id FROM d UNION SELECT e.y, r.root FROM r JOIN e ON e.x = r.doc_id)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, min(r.root) AS component_id
FROM d JOIN r USING (doc_id) LEFT JOIN n USING (doc_id) GROUP BY d.doc_id, n.n
"""
