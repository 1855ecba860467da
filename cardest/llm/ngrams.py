"""N-gram Jaccard join: rare-first prefix filtering with length, positional and suffix filters, verified once per pair.

Equal word sequences share one node. A document's distinct n-grams are ordered rare first (document frequencies are sums
over all documents in a sketch of fixed width; any order is right, a good one is fast) and only a prefix is joined: two
sets with the wanted similarity share an n-gram of their prefixes. Posting lists never expand into all pairs. They are
worked on in rounds, and after each the proposals that survive the filters are verified, links are contracted, and lists
whose members have become one component are left out. First every list, in order of set size, proposes its neighbours.
Then, in the lists left, the members outside a list's largest component meet all members, in cells of bounded size: once
to propose only the likeliest partner in every other component, and once more, among what is still apart, to propose all.
So no link between two components is lost, and members of one component are not compared with each other.

The suffix filter compares counts of both sets by equal ranges of the hash (a signature of about a byte for four n-grams):
the sum of the lesser counts bounds the intersection. Texts are read again only for pairs that it lets through.
"""

from __future__ import annotations

from collections.abc import Iterator
from fractions import Fraction

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from cardest.llm.common import attach, components, narrow_batches, stored

#: Width of the frequency sketch: two to this power of counters, whatever the data.
SKETCH_BITS = 18
#: Members of a posting list on either side of one cell of comparisons.
BLOCK = 512
#: Names of documents a task remembers, to pass over their copies.
SEEN = 200_000
#: Pairs of one vectorised comparison, and bytes of signatures compared at once.
PAIRS = 500_000
SIGNATURE_BYTES = 8_000_000
#: N-grams a range of the signature holds on average, from 16 ranges on.
PER_RANGE = 4
#: Rows of an Arrow batch where a row holds a text, or two whole sets.
TEXT_ROWS = 1000
WIDE_ROWS = 128
#: Documents whose identifiers may be broadcast to pick texts for verification: 8 bytes each.
BROADCAST_IDS = 2_000_000

_MIX = (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB)


class Shingler:
    """Distinct n-grams of a text's words as sorted 64-bit hashes, and a 128-bit name of the whole word sequence."""

    def __init__(self, n: int, seed: int = 0) -> None:
        self.n, self.seed = n, seed

    def words(self, text: str | None) -> list[bytes]:
        """ASCII letters in lower case, cut at ASCII white space."""
        return (text or "").encode("utf-8", "surrogatepass").lower().split()

    def name(self, words: list[bytes]) -> tuple[int, int]:
        """The 64-bit name of a node, and 64 more bits that tell two texts of one name apart."""
        digest = xxhash.xxh3_128_intdigest(b" ".join(words), seed=self.seed)
        return (digest & (2**64 - 1)) - 2**63, (digest >> 64) - 2**63

    def grams(self, words: list[bytes]) -> np.ndarray:
        if not words:
            return np.empty(0, dtype=np.uint64)
        codes = np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))
        n = min(self.n, len(words))
        a, b, c = (np.uint64(x) for x in _MIX)
        h = np.full(len(words) - n + 1, np.uint64(n), dtype=np.uint64)
        for i in range(n):
            h = (h ^ codes[i : len(codes) - n + 1 + i]) * a
            h ^= h >> np.uint64(29)
        h = (h ^ (h >> np.uint64(30))) * b
        h = (h ^ (h >> np.uint64(27))) * c
        return np.unique(h ^ (h >> np.uint64(31)))


def prefix_length(size: int, t: Fraction) -> int:
    """N-grams of which one at least is shared with any set of similarity ``t`` or more: size - ceil(t size) + 1."""
    return size - -(-t.numerator * size // t.denominator) + 1 if size else 0


def least_overlap(a, b, t: Fraction):
    """Smallest intersection of sets of these sizes with similarity ``t``: ceil(t (a + b) / (1 + t))."""
    return -(-(t.numerator * (a + b)) // ((t.numerator + t.denominator)))


def signature(grams: np.ndarray) -> bytes:
    """How many n-grams fall into each of equal ranges of the hash, a byte a range (255: that many or more); a power of two
    of ranges."""
    bits = max(4, max(0, len(grams) // PER_RANGE - 1).bit_length())
    counts = np.bincount((grams >> np.uint64(64 - bits)).astype(np.int64), minlength=1 << bits)
    return np.minimum(counts, 255).astype(np.uint8).tobytes()


class Signatures:
    """Signatures of some nodes, kept by width."""

    def __init__(self, signatures: list[bytes]) -> None:
        self.width = np.fromiter(map(len, signatures), np.int64, len(signatures))
        self.row, self.tables = np.zeros(len(signatures), np.int64), {}
        for w in np.unique(self.width).tolist():
            here = np.flatnonzero(self.width == w)
            self.row[here] = np.arange(len(here))
            self.tables[w] = np.frombuffer(b"".join([signatures[k] for k in here]), np.uint8).reshape(-1, w)

    def room(self, i: np.ndarray, j: np.ndarray, t: Fraction) -> np.ndarray:
        """By how many n-grams the bound of the pairs' intersections exceeds what ``t`` needs; below 0 a pair is no link.

        Where a range is full its count is unknown, and the pair has all room.
        """
        out, kinds = np.zeros(len(i), np.int64), self.width[i] * (1 << 32) + self.width[j]
        for kind in np.unique(kinds).tolist():
            here, (wide, thin) = np.flatnonzero(kinds == kind), divmod(kind, 1 << 32)
            least, step = min(wide, thin), max(1, SIGNATURE_BYTES // max(wide, thin))
            for at in range(0, len(here), step):
                k = here[at : at + step]
                x, y = self.tables[wide][self.row[i[k]]], self.tables[thin][self.row[j[k]]]
                full = (x.max(axis=1) == 255) | (y.max(axis=1) == 255)
                need = least_overlap(x.sum(axis=1, dtype=np.int64), y.sum(axis=1, dtype=np.int64), t)
                x, y = (v if v.shape[1] == least else v.reshape(len(v), least, -1).sum(axis=2, dtype=np.int32) for v in (x, y))
                out[k] = np.where(full, 1 << 40, np.minimum(x, y).sum(axis=1, dtype=np.int64) - need)
        return out


def similar(x: np.ndarray, y: np.ndarray, t: Fraction) -> bool:
    """Whether intersection / union reaches ``t``, exactly."""
    need = least_overlap(len(x), len(y), t)
    return min(len(x), len(y)) >= need and len(np.intersect1d(x, y, assume_unique=True)) >= need


def near_copies(docs: DataFrame, n: int = 5, threshold: Fraction = Fraction(4, 5), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Class of every document under links of n-gram Jaccard similarity ``threshold`` or more.

    Returns ``doc_id, n_shingles, component_id``, one row per input row: the number of distinct n-grams and the smallest
    identifier reachable by links, its own included. A document of fewer than ``n`` words has its whole sequence as one
    n-gram; a null text, or one without words, has none and is linked with nothing. Rows that repeat an identifier are one
    node's copies; a null identifier never becomes the smallest unless all of its class have none. N-grams are compared by
    64-bit hashes: a false match needs a collision within one pair of documents. Two word sequences that get the same
    64-bit name are noticed and all names drawn anew. An empty table gives an empty result.
    """
    t = Fraction(threshold)
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    for seed in range(8):
        rows, sketch = _read(base, n, seed)
        if rows.groupBy("node").agg(F.min("check").alias("lo"), F.max("check").alias("hi")).where("lo <> hi").isEmpty():
            break
    else:
        raise RuntimeError("near_copies: two texts shared a 64-bit name with each of eight seeds")
    nodes = stored(rows.where("n_shingles > 0").groupBy("node").agg(F.min("doc_id").alias("doc_id"), F.min("signature").alias("signature")), "ngram-names")
    lists = _posting_lists(base, n, seed, sketch, t)
    verifier = _Verifier(base, nodes, n, seed, t)
    verifier.add(_neighbour_pairs(lists.where("strong"), t))
    lists = stored(_undecided(lists, verifier.classes()), "ngram-lists")
    if verifier.add(_residual_pairs(lists, nodes, t, likeliest=True)):
        lists = stored(_undecided(lists, verifier.classes()), "ngram-lists")
    verifier.add(_residual_pairs(lists, nodes, t))
    roots = nodes.select("node", "doc_id").join(verifier.classes(), "node", "left").select("node", F.coalesce("root", "node").alias("root"), "doc_id")
    least = roots.groupBy("root").agg(F.min("doc_id").alias("component_id"))
    classes = roots.join(least, "root").select("node", "component_id")
    out = attach(rows.where("n_shingles > 0").select("doc_id", "node", "n_shingles"), "node", "doc_id", classes).select("doc_id", "n_shingles", "component_id")
    alone = rows.where("n_shingles = 0").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    return out.unionByName(alone)


def _read(base: DataFrame, n: int, seed: int) -> tuple[DataFrame, np.ndarray]:
    """Name, set size and signature of every document, and the document frequencies of all n-grams in the sketch."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        shingler, counters = Shingler(n, seed), np.zeros(2**SKETCH_BITS, dtype=np.int64)
        for b in batches:
            sizes, nodes, checks, signatures = [], [], [], []
            for text in b["text"]:
                words = shingler.words(text)
                grams = shingler.grams(words)
                np.add.at(counters, (grams >> np.uint64(64 - SKETCH_BITS)).astype(np.int64), 1)
                node, check = shingler.name(words)
                sizes.append(len(grams))
                nodes.append(node)
                checks.append(check)
                signatures.append(signature(grams) if len(grams) else None)
            yield pd.DataFrame({"kind": 0, "doc_id": b["doc_id"].astype("Int64"), "node": nodes, "check": checks, "n_shingles": sizes, "signature": signatures})
        hit = np.flatnonzero(counters)
        yield pd.DataFrame({"kind": 1, "doc_id": pd.array(hit, dtype="Int64"), "node": counters[hit], "check": 0, "n_shingles": 0, "signature": None})

    with narrow_batches(base.sparkSession, TEXT_ROWS):
        out = stored(base.mapInPandas(run, "kind int, doc_id bigint, node bigint, check bigint, n_shingles bigint, signature binary"), "ngram-nodes")
    counts = out.where("kind = 1").groupBy("doc_id").agg(F.sum("node").alias("n")).toPandas()  # at most 2**SKETCH_BITS rows
    sketch = np.zeros(2**SKETCH_BITS, dtype=np.int64)
    sketch[counts["doc_id"].to_numpy(dtype=np.int64)] = counts["n"].to_numpy(dtype=np.int64)
    return out.where("kind = 0").drop("kind"), sketch


def _posting_lists(base: DataFrame, n: int, seed: int, sketch: np.ndarray, t: Fraction) -> DataFrame:
    """Prefix n-grams that two nodes at least share: ``gram, node, size, pos, strong`` and the neighbour before.

    ``strong`` marks positions early enough to be the first one shared with a set of the same size; neighbours are taken
    among strong members, ordered by size.
    """
    order = base.sparkSession.sparkContext.broadcast(np.minimum(sketch, 2**31 - 1).astype(np.int32))  # 4 * 2**SKETCH_BITS bytes

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        shingler, frequency, seen = Shingler(n, seed), order.value, set()
        for b in batches:
            out: list[list] = [[], [], [], []]
            for text in b["text"]:
                words = shingler.words(text)
                if not words:
                    continue
                node = shingler.name(words)[0]
                if node in seen:  # copies in one task; others meet in their posting lists
                    continue
                if len(seen) > SEEN:
                    seen.clear()
                seen.add(node)
                grams = shingler.grams(words)
                k = prefix_length(len(grams), t)
                f = frequency[(grams >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)]
                head = np.argsort(f, kind="stable")[:k]  # hashes are sorted already
                out[0].append(grams[head].view(np.int64))
                out[1].append(np.full(k, node, dtype=np.int64))
                out[2].append(np.full(k, len(grams), dtype=np.int32))
                out[3].append(np.arange(k, dtype=np.int32))
            if out[0]:
                gram, who, size, pos = map(np.concatenate, out)
                yield pd.DataFrame({"gram": gram, "node": who, "size": size, "pos": pos})

    rows = base.mapInPandas(run, "gram bigint, node bigint, size int, pos int")
    w = W.partitionBy("gram").orderBy("size", "node")
    rows = rows.withColumn("before", F.lag("node").over(w)).where("before is null or before <> node")  # copies in other tasks
    rows = rows.withColumn("after", F.lead("node").over(w)).where("before is not null or after is not null")
    strong = F.expr(f"(size - pos) * {t.numerator + t.denominator} >= {2 * t.numerator} * size")
    with narrow_batches(base.sparkSession, TEXT_ROWS):
        return stored(rows.select("gram", "node", "size", "pos", strong.alias("strong")), "ngram-lists")


def _undecided(lists: DataFrame, classes: DataFrame) -> DataFrame:
    """The lists whose members are of more than one component, with each member's ``root``."""
    rows = lists.select("gram", "node", "size", "pos")
    if classes.count() <= BROADCAST_IDS:
        rows = rows.join(F.broadcast(classes), "node", "left")
    else:
        rows = attach(rows, "node", "gram", classes)
    rows = rows.select("gram", "node", "size", "pos", F.coalesce("root", "node").alias("root"))
    w = W.partitionBy("gram")
    return rows.withColumn("low", F.min("root").over(w)).withColumn("high", F.max("root").over(w)).where("low <> high").drop("low", "high")


def _passes(rows: DataFrame, t: Fraction) -> DataFrame:
    """Length and positional filter on ``size, pos`` and ``size2, pos2``: what is left behind the shared n-gram must do."""
    need = f"(size + size2) * {t.numerator}"
    room = f"least(size - pos, size2 - pos2) * {t.numerator + t.denominator}"
    return rows.where(f"{room} >= {need}").where(f"least(size, size2) * {t.denominator} >= greatest(size, size2) * {t.numerator}")


def _neighbour_pairs(lists: DataFrame, t: Fraction) -> DataFrame:
    """Members next to each other in a list, by set size: at most one pair a member."""
    last = F.lag(F.struct("node", "size", "pos")).over(W.partitionBy("gram").orderBy("size", "node"))
    rows = lists.withColumn("last", last).where("last is not null")
    rows = rows.select("node", "size", "pos", F.col("last.node").alias("node2"), F.col("last.size").alias("size2"), F.col("last.pos").alias("pos2"))
    return _passes(rows, t).select(F.greatest("node", "node2").alias("a"), F.least("node", "node2").alias("b")).distinct()


def _residual_pairs(lists: DataFrame, nodes: DataFrame, t: Fraction, likeliest: bool = False) -> DataFrame:
    """Pairs of different components that share a prefix n-gram and pass all filters.

    In every list, members outside its largest component (the list's main one) meet all members. Both sides are dealt into
    blocks of about ``BLOCK``, and a cell is a block of either side, over all lists with one main component; a node's
    signature comes once a cell. A cell's pairs are compared there, and only those that pass leave it; with ``likeliest``,
    for every asking member and other component only the pair with most room.
    """
    sizes = lists.groupBy("gram", "root").agg(F.count("*").alias("m"))
    split = sizes.groupBy("gram").agg(F.sum("m").alias("m"), F.max(F.struct("m", "root")).alias("most")).select("gram", "m", F.col("most.root").alias("main"), (F.col("m") - F.col("most.m")).alias("out"))
    grid = split.groupBy("main").agg(F.ceil(F.max("m") / BLOCK).cast("int").alias("blocks"), F.ceil(F.max("out") / BLOCK).cast("int").alias("asks"))
    # one row a list meets its grid, then the members meet one row a list: a large component's lists stay spread out
    rows = lists.join(split.select("gram", "main").join(grid, "main"), "gram").withColumn("outside", F.col("root") != F.col("main"))

    def every(n: str):
        return F.explode(F.sequence(F.lit(0), F.col(n) - 1))

    def own(n: str):
        return F.pmod(F.xxhash64("node"), F.col(n)).cast("int")

    cell = ["main", "block", "ask"]
    columns = [*cell, "gram", "asking", "outside", "node", "size", "pos", "root"]
    members = rows.withColumn("block", own("blocks")).withColumn("ask", every("asks")).withColumn("asking", F.lit(False)).select(*columns)
    asking = rows.where("outside").withColumn("ask", own("asks")).withColumn("block", every("blocks")).withColumn("asking", F.lit(True)).select(*columns)
    both = members.unionByName(asking)
    known = both.select(*cell, "node").distinct().join(nodes.select("node", "signature"), "node")
    both = both.withColumn("signature", F.lit(None).cast("binary")).unionByName(
        known.select(*cell, F.lit(0).cast("long").alias("gram"), F.lit(False).alias("asking"), F.lit(False).alias("outside"), "node", F.lit(0).alias("size"), F.lit(0).alias("pos"), F.lit(0).cast("long").alias("root"), "signature")
    )
    # a cell's signatures come before its lists
    both = both.withColumn("row", F.col("signature").isNull()).repartition(*cell).sortWithinPartitions(*cell, "row", "gram", "asking")

    def compare(c: dict[str, np.ndarray], signatures: Signatures) -> pd.DataFrame:
        """All asking rows of whole lists against the members there, some hundred thousand pairs at a time."""
        new = (c["gram"][1:] != c["gram"][:-1]) | (c["cell"][1:] != c["cell"][:-1])
        edge = np.flatnonzero(np.r_[True, new])
        group = np.r_[0, np.cumsum(new)]
        members = np.add.reduceat((~c["asking"]).astype(np.int64), edge)  # they come first in a list
        asking = np.flatnonzero(c["asking"])
        fan = members[group[asking]]
        roots = np.zeros(len(c["names"]), np.int64)
        roots[c["at"]] = c["root"]
        upto, at, made = np.cumsum(fan), 0, [pd.DataFrame({"a": np.empty(0, np.int64), "b": np.empty(0, np.int64)})]
        while at < len(asking):
            end = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + PAIRS, side="right")))
            n = fan[at:end]
            i = np.repeat(asking[at:end], n)
            j = np.repeat(edge[group[asking[at:end]]], n) + np.arange(len(i)) - np.repeat(np.cumsum(n) - n, n)
            least, most = np.minimum(c["size"][i], c["size"][j]), np.maximum(c["size"][i], c["size"][j])
            room = np.minimum(c["size"][i] - c["pos"][i], c["size"][j] - c["pos"][j])
            ok = (room * (t.numerator + t.denominator) >= (least + most) * t.numerator) & (least * t.denominator >= most * t.numerator) & (c["root"][i] != c["root"][j])
            ok &= ~c["outside"][j] | (c["node"][i] > c["node"][j])
            x, y = np.divmod(np.unique(c["at"][i[ok]] << 32 | c["at"][j[ok]]), 1 << 32)
            room = signatures.room(x, y, t)
            x, y, room = x[room >= 0], y[room >= 0], room[room >= 0]
            if likeliest:
                theirs = roots[y]
                order = np.lexsort((-room, theirs, x))
                x, y, theirs = x[order], y[order], theirs[order]
                first = np.r_[True, (x[1:] != x[:-1]) | (theirs[1:] != theirs[:-1])][: len(x)]
                x, y = x[first], y[first]
            made.append(pd.DataFrame({"a": c["names"][x], "b": c["names"][y]}))
            at = end
        return pd.concat(made).drop_duplicates()

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        """Rows come sorted by cell and list; the last list of a batch waits for the next one, with its cell's signatures."""
        held = None
        for b in batches:
            b = b if held is None else pd.concat([held, b], ignore_index=True)
            if not len(b):
                continue
            new = (b[cell].to_numpy()[1:] != b[cell].to_numpy()[:-1]).any(axis=1)
            b["cell"] = np.r_[0, np.cumsum(new)]
            last = b["cell"].iat[-1]
            waits = ((b["cell"] == last) & ((b["gram"] == b["gram"].iat[-1]) | ~b["row"])).to_numpy()
            yield pairs(b[~waits | ~b["row"].to_numpy()])
            held = b[waits].drop(columns="cell")
        if held is not None:
            held["cell"] = 0
            yield pairs(held)

    def pairs(b: pd.DataFrame) -> pd.DataFrame:
        lists = b[b["row"]]
        if not len(lists):
            return pd.DataFrame({"a": np.empty(0, np.int64), "b": np.empty(0, np.int64)})
        known = b[~b["row"]].drop_duplicates("node")
        index = pd.Index(known["node"])
        c = {x: lists[x].to_numpy() for x in ("cell", "gram", "asking", "outside", "node", "root")} | {x: lists[x].to_numpy(np.int64) for x in ("size", "pos")}
        c |= {"at": index.get_indexer(lists["node"]).astype(np.int64), "names": index.to_numpy()}
        return compare(c, Signatures(known["signature"].tolist()))

    made = both.mapInPandas(run, "a bigint, b bigint")
    return made.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


class _Verifier:
    """Verified links so far, and what was fetched to find them: every text is read and every pair compared at most once."""

    def __init__(self, base: DataFrame, nodes: DataFrame, n: int, seed: int, t: Fraction) -> None:
        self.base, self.nodes, self.n, self.seed, self.t = base, nodes, n, seed, t
        self.spark: SparkSession = base.sparkSession
        empty = self.spark.range(0).where("false")
        self.links = self.tested = empty.select(F.col("id").alias("a"), F.col("id").alias("b"))
        self.sets = empty.select(F.col("id").alias("node"), F.lit(b"").alias("grams"))
        self.found: DataFrame | None = None

    def classes(self) -> DataFrame:
        """``node, root`` of all nodes with a link."""
        if self.found is None:
            self.found = stored(components(self.links), "ngram-classes")
        return self.found

    def add(self, pairs: DataFrame) -> bool:
        """Verify proposed pairs; whether there are links among them."""
        pairs = stored(self._likely(pairs.join(self.tested, ["a", "b"], "left_anti")), "ngram-pairs")
        if pairs.isEmpty():
            return False
        self.tested = self.tested.unionByName(pairs)
        self._fetch(pairs)
        n, t = self.n, self.t

        def check(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for b in batches:
                good = [similar(np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64), t) for x, y in zip(b["x"], b["y"], strict=True)]
                yield b.loc[good, ["a", "b"]]

        both = pairs.join(self.sets.select(F.col("node").alias("b"), F.col("grams").alias("y")), "b").join(self.sets.select(F.col("node").alias("a"), F.col("grams").alias("x")), "a")
        with narrow_batches(self.spark, WIDE_ROWS):
            links = stored(both.select("a", "b", "x", "y").mapInPandas(check, "a bigint, b bigint"), "ngram-links")
        if links.isEmpty():
            return False
        self.links, self.found = self.links.unionByName(links), None
        return True

    def _likely(self, pairs: DataFrame) -> DataFrame:
        """The pairs whose signatures allow the threshold."""
        t, ends = self.t, self.nodes.select("node", "signature")

        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for b in batches:
                i = np.arange(len(b))
                yield b.loc[Signatures([*b["x"], *b["y"]]).room(i, i + len(b), t) >= 0, ["a", "b"]]

        both = pairs.join(ends.toDF("a", "x"), "a").join(ends.toDF("b", "y"), "b")
        return both.select("a", "b", "x", "y").mapInPandas(run, "a bigint, b bigint")

    def _fetch(self, pairs: DataFrame) -> None:
        """Sets of the pairs' nodes that no earlier round has fetched."""
        n, seed = self.n, self.seed
        wanted = pairs.select(F.col("a").alias("node")).unionByName(pairs.select(F.col("b").alias("node"))).distinct().join(self.sets.select("node"), "node", "left_anti")
        wanted = stored(wanted.join(self.nodes.select("node", "doc_id"), "node"), "ngram-wanted")
        n_wanted = wanted.count()
        if not n_wanted:
            return
        texts = self.base.join(F.broadcast(wanted) if n_wanted <= BROADCAST_IDS else wanted, self.base["doc_id"].eqNullSafe(wanted["doc_id"])).select("node", "text")

        def sets(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            shingler = Shingler(n, seed)
            for b in batches:
                words = [shingler.words(x) for x in b["text"]]
                mine = [shingler.name(w)[0] == node for w, node in zip(words, b["node"], strict=True)]
                yield pd.DataFrame({"node": b["node"], "grams": [shingler.grams(w).tobytes() for w in words]})[mine]

        with narrow_batches(self.spark, TEXT_ROWS):
            grams = stored(texts.mapInPandas(sets, "node bigint, grams binary"), "ngram-sets")
        if grams.count() > n_wanted:  # rows that repeat an identifier and its text
            grams = stored(grams.dropDuplicates(["node"]), "ngram-sets")
        self.sets = self.sets.unionByName(grams)
