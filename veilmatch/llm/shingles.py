"""Near copies by word shingles: every pair of documents whose shingle sets reach a Jaccard similarity.

A set is put in one global order, shingles that a sample shows to be frequent last and the others by hash. Two
sets of similarity p/q or more then share a shingle among the first ``n - ceil(n p / q) + 1`` of either,
so documents that meet at such a shingle are all candidates there are. The set whose first shingles end earlier in
the order can share only the rest of it beyond those that the two heads share; that bounds what they share at all. Candidates
below the bound are left out, and the others are checked on their whole sets. Nothing depends on chance: the sample only changes the order, and with it the time.

``near_copies`` links by SimHash fingerprints first, as op7 does, and by this filter what the fingerprints leave apart: its
groups are connected by either link.

Scale: equal sets collapse before pairs are looked for. Keys are dealt to ``ROUNDS`` rounds, and checks to as many; what a round has shuffled leaves the disks
before the next. Members of a large key are first held against a few of them, which connects
near copies by as many couples as there are members; then only couples between different components are formed. A task reads whole texts and emits the head of each set; whole
sets are made again only for one document of each set that has a candidate (a bitmap of ``MARKS`` bits tells them, and a few more).

Defined cases: words are cut at blanks, ASCII letters compared without case; a text of fewer words than a shingle is one shingle;
texts without a word are copies of each other; repeated rows and equal ids keep their rows; an empty table gives no
rows; a null id takes no part in naming a component unless alone.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from veilmatch.llm import simhash
from veilmatch.llm.common import durable, released, removed, short_batches, tidy, written
from veilmatch.llm.components import components
from veilmatch.llm.contamination import groups
from veilmatch.llm.superkmers import as_words, mixed

WORDS, SIMILAR = 5, (4, 5)  # shingle length; least similarity as a fraction
SAMPLE, OFTEN, FREQUENT = 10_000, 5, 100_000  # sampled documents; how many of them make a shingle frequent; shingles kept
MARKS = 1 << 26  # bits
ROUNDS = 4  # parts of the keys, and of the checks, that are on the disks at a time
CHECKS = 1 << 20  # most couples of a round of checks, of 16 bytes
PAIRS = 1 << 18  # pairs of members that a task looks at together, beside those of one member
LARGE, LEADERS = 8, 2  # members that make a key large; members that all others of it are held against first


def shingle_sets(texts: list[str | None], words: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashes of each text's shingles, ascending within a text, and where each text's begin and end."""
    s = as_words([(t or "").encode().lower() for t in texts])
    n = np.diff(s.ends)
    text = np.repeat(np.arange(len(texts)), n)
    at = np.arange(len(text))
    whole = at + words <= s.ends[1:][text]
    hashes, owner = [mixed(s.hashes(at[whole], words))], [text[whole]]
    for k in range(1, words):
        short = np.flatnonzero(n == k)
        if len(short):
            hashes.append(mixed(s.hashes(s.ends[:-1][short], k) + np.uint64(k)))
            owner.append(short)
    h, o = np.concatenate(hashes), np.concatenate(owner)
    order = np.lexsort((h, o))
    h, o = h[order], o[order]
    if len(h):
        new = np.concatenate(([True], (h[1:] != h[:-1]) | (o[1:] != o[:-1])))
        h, o = h[new], o[new]
    return h, np.searchsorted(o, np.arange(len(texts) + 1))


def _sets(batches: Iterator[pa.RecordBatch], column: int, words: int) -> Iterator[tuple[pa.RecordBatch, int, np.ndarray, np.ndarray]]:
    for batch in batches:
        for lo in range(0, batch.num_rows, 1000):
            part = batch.slice(lo, 1000)
            for first, texts in groups(part.column(column).to_pylist()):
                yield part, first, *shingle_sets(texts, words)


def _names(h: np.ndarray, ends: np.ndarray) -> np.ndarray:
    return np.array([xxhash.xxh64_intdigest(h[a:b].tobytes(), 42) for a, b in zip(ends[:-1].tolist(), ends[1:].tolist())], np.uint64).view(np.int64)


def frequent_shingles(plain: DataFrame, words: int) -> np.ndarray:
    documents = plain.count()
    share = int(1_000_000 * min(1.0, SAMPLE / max(1, documents)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, _, h, _ in _sets(batches, 0, words):
            yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64))], names=["h"])

    sample = plain.where(F.pmod(F.xxhash64("doc_id", F.lit(23)), F.lit(1_000_000)) < share).select("text")
    counted = sample.mapInArrow(tidy(run), "h long").groupBy("h").count().where(F.col("count") >= OFTEN)
    rows = counted.orderBy(F.desc("count"), "h").limit(FREQUENT).collect()
    return np.sort(np.array([r["h"] for r in rows], np.int64).view(np.uint64))


def heads(plain: DataFrame, often: np.ndarray, words: int, p: int, q: int, prints: bool = False) -> DataFrame:
    """(doc_id, node, n, head, fingerprint): node names the set, n is its size, head its first shingles in the global order.

    The fingerprint is op7's of the text, null if ``prints`` is false.
    """
    sent = plain.sparkSession.sparkContext.broadcast(often)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        late = sent.value
        for part, first, h, ends in _sets(batches, 1, words):
            n = np.diff(ends)
            own = part.slice(first, len(n))
            marks = pa.array(simhash.fingerprints_of(own.column(1).to_pylist()).view(np.int64)) if prints else pa.nulls(len(n), pa.int64())
            owner = np.repeat(np.arange(len(n)), n)
            last = np.zeros(len(h), bool)
            if len(late):
                last = late[np.minimum(np.searchsorted(late, h), len(late) - 1)] == h
            order = np.lexsort((last, owner))  # stable: hashes stay ascending
            keep = n - -(-n * p // q) + 1
            keep[n == 0] = 0
            place = np.arange(len(h)) - ends[:-1][owner]
            taken = h[order][place < keep[owner]].view(np.int64)
            head = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(keep))).astype(np.int32)), pa.array(taken))
            yield pa.RecordBatch.from_arrays([own.column(0), pa.array(_names(h, ends)), pa.array(n.astype(np.int32)), head, marks], names=["doc_id", "node", "n", "head", "fingerprint"])

    return plain.select("doc_id", "text").mapInArrow(tidy(run), "doc_id long, node long, n int, head array<long>, fingerprint long")


def _by_key(entries: DataFrame, run: Callable[[np.ndarray, ...], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """``run`` on the columns of all entries of some keys at a time; the entries of a key stand together."""

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces = []  # of the key that may go on in the next batch
        for batch in batches:
            if not batch.num_rows:
                continue
            now = [c.to_numpy() for c in batch.columns]
            pieces.append(now)
            if now[0][0] == now[0][-1] == pieces[0][0][-1]:
                continue
            held = [np.concatenate(c) for c in zip(*pieces)]
            cut = int(np.flatnonzero(held[0] != held[0][-1])[-1]) + 1
            yield from run(*(c[:cut] for c in held))
            pieces = [[c[cut:] for c in held]]
        if pieces:
            yield from run(*(np.concatenate(c) for c in zip(*pieces)))

    return entries.repartition("key").sortWithinPartitions("key").mapInArrow(tidy(task), schema)


def _needed(n: np.ndarray, m: np.ndarray, p: int, q: int) -> np.ndarray:
    """Shingles that heads of sets of sizes n <= m must share: all that are needed less the most that can lie behind the heads."""
    return -(-p * (n + m) // (p + q)) + (p * m // -q) + 1


def _entries(nodes: DataFrame, part: int, *more: str) -> DataFrame:
    keyed = nodes.select("node", "n", *more, F.posexplode("head").alias("place", "key")).where(F.pmod(F.col("key"), F.lit(ROUNDS)) == part)
    return keyed.select("key", "node", "n", *[(F.col("n") - F.col("place")).alias("rest")] * ("label" in more), *more)


def _rounds(one: Callable[[int], DataFrame], parts: int = ROUNDS) -> DataFrame:
    """All rows of ``one(part)`` over the parts, one after the other."""
    return reduce(DataFrame.unionAll, [released(durable(one(part))) for part in range(parts)])


def _pieces(ask: np.ndarray, wide: np.ndarray, most: int = PAIRS) -> list[np.ndarray]:
    """``ask`` in runs whose pairs, ``wide`` of each, are fewer than ``most`` and those of one more."""
    number = np.cumsum(wide) // most
    return np.split(ask, np.flatnonzero(number[1:] != number[:-1]) + 1) if len(ask) else []


def stars(nodes: DataFrame, p: int, q: int) -> DataFrame:
    """Couples (a, b, met) of each member of a large key with LEADERS of its members, the same in keys of the same members.

    Large keys are those of near copies; these couples connect them, as many as members and not as pairs of members. Nodes of one ``label`` need none.
    """

    def run(key: np.ndarray, node: np.ndarray, n: np.ndarray, rest: np.ndarray, label: np.ndarray) -> Iterator[pa.RecordBatch]:
        begins = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
        sizes = np.diff(np.concatenate((begins, [len(key)])))
        large = sizes >= LARGE
        if not large.any():
            return
        keep = np.repeat(large, sizes)
        node, n, label, sizes = node[keep], n[keep].astype(np.int64), label[keep], sizes[large]
        begins = np.cumsum(sizes) - sizes
        group = np.repeat(np.arange(len(sizes)), sizes)
        for seed in range(LEADERS):
            order = np.lexsort((mixed(node.view(np.uint64) + np.uint64(seed)), group))
            leader = order[begins][group]
            low, high = np.minimum(n, n[leader]), np.maximum(n, n[leader])
            good = (label != label[leader]) & (high * p <= low * q)
            a, b = node[good], node[leader[good]]
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], names=["a", "b"])

    met = _rounds(lambda part: _by_key(_entries(nodes, part, "label"), run, "a long, b long").groupBy("a", "b").agg(F.count("*").alias("met")))
    return met.groupBy("a", "b").agg(F.sum("met").alias("met"))


def candidates(nodes: DataFrame, p: int, q: int) -> DataFrame:
    """Distinct couples (a, b, met) of nodes of different ``label`` that meet at so many shingles of their heads that they may be similar."""

    def run(key: np.ndarray, node: np.ndarray, n: np.ndarray, rest: np.ndarray, label: np.ndarray) -> Iterator[pa.RecordBatch]:
        order = np.lexsort((label, key))
        key, node, n, rest, label = key[order], node[order], n[order].astype(np.int64), rest[order].astype(np.int64), label[order]
        new = np.concatenate(([True], key[1:] != key[:-1]))
        begins = np.flatnonzero(new)
        sizes = np.diff(np.concatenate((begins, [len(key)])))
        group = np.cumsum(new) - 1
        # Runs of one label in a key; couples lie between runs, so all members but those of the longest run look for theirs.
        run_new = new | np.concatenate(([True], label[1:] != label[:-1]))
        number = np.cumsum(run_new) - 1
        length = np.bincount(number)[number]
        longest = np.maximum.reduceat(length, begins)[group]
        first = np.minimum.reduceat(np.where(length == longest, number, len(key)), begins)[group]
        minor = number != first
        ask = np.flatnonzero(minor)
        for part in _pieces(ask, sizes[group[ask]]):
            wide = sizes[group[part]]
            i = np.repeat(part, wide)
            j = np.arange(wide.sum()) - np.repeat(np.cumsum(wide) - wide, wide) + begins[group[i]]
            # Two that both look for the other meet once.
            keep = (label[i] != label[j]) & (~minor[j] | (i < j))
            i, j = i[keep], j[keep]
            i, j = np.where(n[i] <= n[j], i, j), np.where(n[i] <= n[j], j, i)
            keep = n[j] * p <= n[i] * q
            i, j = i[keep], j[keep]
            least = _needed(n[i], n[j], p, q)
            # Where one is enough, the first that the two share leaves room for the others.
            good = (least > 1) | (np.minimum(rest[i], rest[j]) * (p + q) >= p * (n[i] + n[j]))
            if good.any():
                a, b = node[i[good]], node[j[good]]
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b)), pa.array(least[good])], names=["a", "b", "least"])

    met = _rounds(lambda part: _by_key(_entries(nodes, part, "label"), run, "a long, b long, least long").groupBy("a", "b", "least").agg(F.count("*").alias("met")))
    return met.groupBy("a", "b", "least").agg(F.sum("met").alias("met")).where("met >= least").select("a", "b", "met")


def _places(node: pa.Array, doc: pa.Array) -> np.ndarray:
    """Bit of a set and of the document that stands for it."""
    return mixed(node.to_numpy().view(np.uint64) ^ mixed(doc.fill_null(0).to_numpy().view(np.uint64))) & np.uint64(MARKS - 1)


def _set(bits: np.ndarray, places: np.ndarray) -> np.ndarray:
    return bits[places >> np.uint64(3)] >> (places & np.uint64(7)).astype(np.uint8) & np.uint8(1)


def _marked(chosen: DataFrame) -> np.ndarray:
    """Bits of all (node, doc_id)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = np.zeros(MARKS // 8, np.uint8)
        for batch in batches:
            at = _places(*batch.columns)
            np.bitwise_or.at(bits, at >> np.uint64(3), np.uint8(1) << (at & np.uint64(7)).astype(np.uint8))
        yield pa.RecordBatch.from_arrays([pa.array([bits.tobytes()], pa.binary())], names=["bits"])

    out = np.zeros(MARKS // 8, np.uint8)
    for r in chosen.coalesce(4).mapInArrow(tidy(run), "bits binary").toLocalIterator():
        out |= np.frombuffer(r["bits"], np.uint8)
    return out


def _nodes(couples: DataFrame) -> DataFrame:
    return couples.select(F.explode(F.array("a", "b")).alias("node")).distinct()


def whole_sets(plain: DataFrame, nodes: DataFrame, couples: DataFrame, words: int) -> tuple[DataFrame, str]:
    """(node, held): the sets of all nodes that have a candidate, made from the document that stands for each; and the folder that holds them.

    A few more are there, and a set again where rows are equal in id and text; nothing is exchanged for them.
    """
    sent = plain.sparkSession.sparkContext.broadcast(_marked(nodes.select("node", "doc_id").join(_nodes(couples), "node", "left_semi")))

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, first, h, ends in _sets(batches, 1, words):
            names = _names(h, ends)
            some = np.flatnonzero(_set(sent.value, _places(pa.array(names), part.column(0).slice(first, len(names)))))
            yield pa.RecordBatch.from_arrays([pa.array(names[some]), pa.array([h[ends[i] : ends[i + 1]].tobytes() for i in some], pa.binary())], names=["node", "held"])

    with short_batches(plain.sparkSession):
        return written(plain.select("doc_id", "text").mapInArrow(tidy(whole), "node long, held binary"))


def similar(couples: DataFrame, sets: DataFrame, p: int, q: int) -> DataFrame:
    """The couples whose whole sets reach the similarity; a round sends the two sets of each of its couples once."""

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last = None  # (a, b, set) of the first side
        for batch in batches:
            found = []
            for a, b, side, held in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist(), batch.column(3)):
                held = np.frombuffer(held.as_buffer(), np.uint64)
                if not side:
                    last = (a, b, held)
                elif last is not None and last[:2] == (a, b):
                    x = last[2]
                    both = len(np.intersect1d(x, held, assume_unique=True))
                    if both * (p + q) >= p * (len(x) + len(held)):
                        found.append((a, b))
            if last is not None:
                last = (*last[:2], last[2].copy())  # not a view that holds the batch
            yield pa.RecordBatch.from_arrays([pa.array([f[k] for f in found], pa.int64()) for k in range(2)], names=["a", "b"])

    parts = max(ROUNDS, -(-couples.count() // CHECKS))

    def one(part: int) -> DataFrame:
        some = F.broadcast(couples.where(F.pmod(F.xxhash64("a", "b"), F.lit(parts)) == part).select("a", "b"))
        sides = [sets.select(F.col("node").alias(c), "held").join(some, c).select("a", "b", F.lit(k).alias("side"), "held") for k, c in enumerate("ab")]
        return sides[0].unionAll(sides[1]).repartition("a", "b").sortWithinPartitions("a", "b", "side").mapInArrow(tidy(compare), "a long, b long")

    with short_batches(couples.sparkSession):
        return _rounds(one, parts)


def spanning(couples: DataFrame, sets: DataFrame, p: int, q: int) -> DataFrame:
    """Similar couples that connect all that similar couples connect.

    Each round checks the best couples of every node, and couples of one component need no check any more: a large
    group of near copies takes about as many checks as it has members. Rounds end when no couple is left.
    """
    rest, links, width = couples, None, 1
    while not rest.isEmpty():
        both = rest.select("a", "b", "met", F.explode(F.array("a", "b")).alias("node"))
        rank = F.row_number().over(Window.partitionBy("node").orderBy(F.desc("met"), "a", "b"))
        chosen = durable(both.withColumn("rank", rank).where(F.col("rank") <= width).select("a", "b").distinct())
        found = similar(chosen, sets, p, q)
        links = durable(found if links is None else links.union(found))
        labels = components(links)
        of = lambda x: labels.select(F.col("node").alias(x), F.col("label").alias(f"of_{x}"))
        left = rest.join(chosen, ["a", "b"], "left_anti").join(of("a"), "a", "left").join(of("b"), "b", "left")
        rest = durable(left.where("not coalesce(of_a = of_b, false)").select("a", "b", "met"))
        width *= 8
    return couples.select("a", "b").where("false") if links is None else links


def print_links(marked: DataFrame) -> DataFrame:
    """Couples (a, b) of nodes that connect what SimHash fingerprints within op7's distance connect."""
    held = marked.select("node", "fingerprint").distinct()
    of = components(simhash.near_links(held.select("fingerprint").distinct())).withColumnRenamed("node", "fingerprint")
    named = held.join(of, "fingerprint", "left").select("node", F.coalesce("label", "fingerprint").alias("label"))
    first = named.groupBy("label").agg(F.min("node").alias("a"))
    return named.join(first, "label").where("a <> node").select("a", F.col("node").alias("b")).distinct()


def _labelled(nodes: DataFrame, links: DataFrame) -> DataFrame:
    known = released(components(links))
    return nodes.join(known, "node", "left").withColumn("label", F.coalesce("label", "node"))


def similar_groups(docs: DataFrame, doc: str = "doc_id", text: str = "text", words: int = WORDS, least: tuple[int, int] = SIMILAR, prints: bool = False) -> DataFrame:
    """(doc_id, component_id) per row; component_id is the smallest id that can be reached over similar pairs, with ``prints`` also over near fingerprints."""
    p, q = least
    spark = docs.sparkSession
    plain = docs.select(F.col(doc).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    with short_batches(spark):
        marked = durable(heads(plain, frequent_shingles(plain, words), words, p, q, prints))
    nodes = marked.groupBy("node").agg(F.min("doc_id").alias("doc_id"), F.first("n").alias("n"), F.first("head").alias("head"))
    links = released(durable(print_links(marked))) if prints else spark.createDataFrame([], "a long, b long")
    # Large groups first, by few couples; then every couple that could still connect two components.
    for meetings in (stars, candidates):
        couples = released(durable(meetings(released(durable(_labelled(nodes, links))), p, q)))
        sets, folder = whole_sets(plain, marked.groupBy("node").agg(F.min("doc_id").alias("doc_id")), couples, words)
        links = links.union(spanning(couples, released(sets), p, q))
        removed(spark, folder)
    named = _labelled(marked.select("doc_id", "node"), links)
    first_id = named.groupBy("label").agg(F.min("doc_id").alias("component_id"))
    return named.join(first_id, "label").select("doc_id", F.coalesce("component_id", "doc_id").alias("component_id"))


def near_copies(docs: DataFrame, doc: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, component_id) per row: near copies by op7's SimHash, and by shingles those that it leaves apart."""
    return similar_groups(docs, doc, text, prints=True)
