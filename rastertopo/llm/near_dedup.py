"""Near-duplicate detection by Order MinHash, verified by banded alignment.

Each text is a sequence of five-word shingles, each labelled with how often it occurred before. A sketch takes, under
one hash function, the ``LEAST`` smallest labelled shingles and keeps them in text order; as the order counts, the
chance of equal sketches follows the edit similarity. Texts with a sketch in common (a bucket) are candidates: with a
share s of common shingles two texts meet with a chance of about 1 - (1 - s ** LEAST) ** SKETCHES. Where one word in
five was replaced, the threshold of a link, s is near 0.2 and the chance above 0.9. Of short texts an edit may leave
hardly a shingle: up to ``SHORT_WORDS`` words they have sketches of two-word shingles as well, and where at most
``SHORT_EDITS`` edits are allowed, texts also share a bucket for each sequence of words left by that many deletions.

Two texts are linked when their word edit distance is at most ``1 - SIMILARITY`` of the longer one's words, found by a
bit-parallel alignment that only looks at the band in which this is possible. Classes are the connected components.

No group is expanded into its pairs. Equal texts are one node. In one of ``STAR_SHARE`` buckets, as their keys fall, the
smallest node is compared with the others, which already joins large groups of near copies; then, in buckets with nodes
of several classes, the nodes that are not of the bucket's most common class are compared with one node of that class.
Of what buckets are mixed still, those of at most ``LIGHT`` nodes give a pair for each node and node of another class
that lengths and the words in ``BINS`` hashed bins, an exact lower bound of the distance, don't rule out. The nodes of
larger ones meet anew by rare words, whatever their buckets: linked texts have all but the edited words in common, so
when the words of each are put in one order, those that fewest nodes have first, they share one of the first few (one more
than the edits allowed). Nodes with such a word in common give a pair if the same bound allows it, in two steps, so that
what travels with each word is small: in the tasks of words by ``BRIEF_BINS`` bins of half a byte, then, where the pairs left meet
what is known of their nodes, by all bins and by a closer bound: which of ``BITS`` bits their words set, of equal words each with a
bit of its own. Only a word of more than ``FREQUENT`` nodes that is still among a text's rarest makes blocks of at most ``BLOCK_NODES`` nodes and ``BLOCK_BYTES``
of text; each task holds two blocks, rules pairs out by the same bound with arrays, aligns a pair at the first such word
that both share, skips it when links found before already join the two, and gives links only. So every link between
texts that share a bucket is found, or known to join texts that already share a class; nothing is capped.

Cases: null and empty texts have no words and equal each other only; texts of one word are one shingle; equal
rows are copies; a repeated doc_id is a row of its own; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import itertools
import zlib
from collections.abc import Iterable

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import KeyFilter, released, slices, text_or_empty, written

SHINGLE, SKETCHES, LEAST, SIMILARITY = 5, 112, 2, 0.8
#: Texts of so many words at most also have ``SHORT_SKETCHES`` sketches of ``SHORT_LEAST`` shingles of two words.
SHORT_WORDS, SHORT_SHINGLE, SHORT_SKETCHES, SHORT_LEAST = 64, 2, 64, 3
#: One in so many buckets is compared with its smallest node first.
STAR_SHARE = 14
#: Bins of hashed words, and bits of them for nodes of large buckets, by which pairs are ruled out before they are aligned.
BINS, BITS = 256, 1 << 14
#: Bins that go with each rare word, what one counts at most, and rare words of earlier tasks that go along.
BRIEF_BINS, BRIEF_MOST, BEFORE = 64, 15, 4
#: Links of so few edits at most are found by what deletions leave of the texts, besides sketches.
SHORT_EDITS = 2
#: Shingles hashed under all functions at once (bounds the memory of a task).
BLOCK = 1 << 13
#: The nodes of buckets of more nodes of several classes meet by their rare words.
LIGHT = 16
#: Counters of words by which they are put in order, and rows in which a task's counters travel.
SLOTS, SLOT_ROWS = 1 << 20, 64
#: Words (with their nodes) that meet in one task, and pairs that it holds before it rules some out.
PART_WORDS, PART_PAIRS = 1 << 16, 1 << 20
#: Pairs that all bins and bits are compared for in one task.
PART_CHECKED = 1 << 17
#: The nodes of words that more than so many nodes may have are compared in blocks.
FREQUENT = 1 << 14
#: The most nodes and the bytes of text of a block (one longer text is a block of its own).
BLOCK_NODES, BLOCK_BYTES, BLOCK_BINS = 2048, 4 << 20, 512
SHORT_SALT = np.int64(0x2545F4914F6CDD1D)


def _multipliers(n: int, seed: int) -> np.ndarray:
    return np.random.default_rng(seed).integers(1, 1 << 32, n, dtype=np.uint32) | np.uint32(1)


class _Words(dict):
    """64-bit hashes of words, of which it keeps some."""

    def __missing__(self, word: str) -> int:
        if len(self) >= 100_000:
            self.clear()
        found = self[word] = xxhash.xxh3_64_intdigest(word.encode("utf-8", "surrogatepass"))
        return found


def word_hashes(words: list[str], known: _Words) -> np.ndarray:
    return np.fromiter(map(known.__getitem__, words), np.uint64, len(words))


def in_bins(hashes: np.ndarray) -> np.ndarray:
    """The words counted in ``BINS`` bins, 127 at most in one."""
    return np.minimum(np.bincount((hashes % np.uint64(BINS)).astype(np.int64), minlength=BINS), 127).astype(np.int8)


def in_bits(labelled: np.ndarray) -> np.ndarray:
    """The ``BITS`` bits, those set that labelled words have."""
    found = np.zeros(BITS, bool)
    found[((labelled >> np.uint64(20)) % np.uint64(BITS)).astype(np.int64)] = True
    return np.packbits(found).view(np.uint64)


def in_brief(bins: np.ndarray) -> bytes:
    """The words of ``in_bins`` counted in ``BRIEF_BINS`` bins, ``BRIEF_MOST`` at most in one, two bins a byte."""
    few = np.minimum(bins.reshape(-1, BRIEF_BINS).sum(axis=0, dtype=np.int64), BRIEF_MOST).astype(np.uint8)
    return (few[::2] | few[1::2] << 4).tobytes()


def from_brief(packed: np.ndarray) -> np.ndarray:
    """The bins that rows of ``in_brief`` hold."""
    return np.stack([packed & 15, packed >> 4], 2).reshape(len(packed), BRIEF_BINS).astype(np.int8)


def labelled_shingles(words: np.ndarray, k: int = SHINGLE) -> np.ndarray:
    """64-bit hashes of the shingles of a sequence of word hashes, each mixed with its number of earlier occurrences."""
    n = len(words) - k + 1
    if n < 1:
        if not len(words):
            return np.zeros(0, np.uint64)
        k, n = len(words), 1
    with np.errstate(over="ignore"):
        out = np.zeros(n, np.uint64)
        for j in range(k):
            out = (out ^ words[j : j + n]) * np.uint64(0x9E3779B97F4A7C15)
            out ^= out >> np.uint64(29)
        order = np.argsort(out, kind="stable")
        ordered = out[order]
        fresh = np.concatenate([[True], ordered[1:] != ordered[:-1]])
        label = np.zeros(n, np.uint64)
        if not fresh.all():
            start = np.maximum.accumulate(np.where(fresh, np.arange(n), 0))
            label[order] = (np.arange(n) - start).astype(np.uint64)
        out = (out ^ (label * np.uint64(0xD6E8FEB86659FD93))) * np.uint64(0xA0761D6478BD642F)
        return out ^ (out >> np.uint64(32))


def order_minhash(shingles: np.ndarray, multipliers: np.ndarray, least: int = LEAST) -> np.ndarray:
    """The 64-bit buckets of a text: for each hash function the ``least`` smallest shingles in text order.

    A function multiplies the upper half of a shingle's hash; of equal values the earlier shingle counts as smaller."""
    n, m = len(shingles), len(multipliers)
    if n == 0:
        return np.zeros(0, np.int64)
    keep = min(least, n)
    high = (shingles >> np.uint64(32)).astype(np.uint32)
    every = np.arange(m)
    values, places = [], []
    for start in range(0, n, BLOCK):
        hashed = high[None, start : start + BLOCK] * multipliers[:, None]
        for _ in range(min(keep, hashed.shape[1])):
            at = hashed.argmin(axis=1)
            values.append(hashed[every, at])
            places.append(at + start)
            hashed[every, at] = np.uint32((1 << 32) - 1)
    chosen = np.stack(places, 1)
    if len(places) > keep:
        chosen = np.take_along_axis(chosen, np.argsort(np.stack(values, 1), axis=1, kind="stable")[:, :keep], 1)
    chosen.sort(axis=1)
    found = shingles[chosen]
    with np.errstate(over="ignore"):
        bucket = np.arange(m, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        for j in range(keep):
            bucket = (bucket ^ found[:, j]) * np.uint64(0xFF51AFD7ED558CCD)
            bucket ^= bucket >> np.uint64(33)
    return bucket.view(np.int64)


def text_buckets(words: np.ndarray, functions: np.ndarray, k: int = SHINGLE, least: int = LEAST, similarity: float = SIMILARITY) -> np.ndarray:
    """The buckets of a sequence of word hashes: its sketches, those of a short text, and those of its deletions."""
    found = [order_minhash(labelled_shingles(words, k), functions, least)]
    if 0 < len(words) <= SHORT_WORDS:
        # Other buckets than those of the long shingles, whatever their words.
        found.append(order_minhash(labelled_shingles(words, SHORT_SHINGLE), functions[:SHORT_SKETCHES], SHORT_LEAST) ^ SHORT_SALT)
        found.append(deletion_keys(words, similarity))
    return np.concatenate(found)


def edit_distance(a: list, b: list, most: int) -> int:
    """The edit distance of two sequences if it is at most ``most``, else ``most + 1``."""
    start, shorter = 0, min(len(a), len(b))
    while start < shorter and a[start] == b[start]:
        start += 1
    end = 0
    while end < shorter - start and a[-1 - end] == b[-1 - end]:
        end += 1
    a, b = a[start : len(a) - end], b[start : len(b) - end]
    if len(a) < len(b):
        a, b = b, a
    if len(a) - len(b) > most:
        return most + 1
    if not b:
        return len(a)
    # Elements of one side only must all be edited: a cheap lower bound.
    rest: dict = {}
    for x in a:
        rest[x] = rest.get(x, 0) + 1
    shared = 0
    for x in b:
        if rest.get(x, 0) > 0:
            rest[x] -= 1
            shared += 1
    if len(a) - shared > most:
        return most + 1
    # No band below the bound can do.
    band = max(16, len(a) - shared)
    while True:
        band = min(band, most)
        found = banded_distance(a, b, band)
        if found <= band or band == most:
            return min(found, most + 1)
        band *= 4


def banded_distance(a: list, b: list, band: int) -> int:
    """The edit distance, len(a) >= len(b), if it is at most ``band``, else ``band + 1``.

    Bit-parallel: a column of the matrix within the band is two integers of vertical differences, which slide down
    one row with each element of b; the last row's or diagonal's distance is carried along."""
    n, m = len(a), len(b)
    if n - m > band:
        return band + 1
    band = min(band, n)
    width = 2 * band + 2
    full = (1 << width) - 1
    where: dict = {}
    for i, x in enumerate(a):
        where[x] = where.get(x, 0) | 1 << i
    up, down = full ^ ((1 << (width - band - 1)) - 1), 0
    distance, diagonal, across = band, 1 << (width - 1), 1 << (width - 2)
    shift, most = band + 1 - width, 2 * band + m - n
    for j, x in enumerate(b):
        mask = where.get(x, 0)
        equal = (mask << -shift if shift < 0 else mask >> shift) & full
        zero = (((equal & up) + up) ^ up | equal | down) & full
        plus = (down | ~(zero | up)) & full
        minus = zero & up
        if j < n - band:
            distance += not zero & diagonal
        else:
            distance += bool(plus & across) - bool(minus & across)
            across >>= 1
        if distance > most:
            return band + 1
        half = zero >> 1
        up = (minus | ~(half | plus)) & full
        down = half & plus
        shift += 1
    return distance if distance <= band else band + 1


def limit_of(n: int, similarity: float) -> int:
    """The most edits of texts of which the longer has n words."""
    return int((1 - similarity) * n + 1e-9)


def most_deletions(n: int, similarity: float, most: int = SHORT_EDITS) -> int:
    """The most edits of a link of a text of n words with one as long or longer, where the longer may have ``most`` at most."""
    longer, found = n, -1
    while limit_of(longer, similarity) <= most and longer - n <= most:
        if longer - n <= limit_of(longer, similarity):
            found = limit_of(longer, similarity)
        longer += 1
    return found


def deletion_keys(words: np.ndarray, similarity: float = SIMILARITY) -> np.ndarray:
    """64-bit buckets of a short text: its sequence of word hashes and what is left by deletions, as many as a link's edits.

    Texts within d edits have a sequence in common that d deletions or fewer leave of either."""
    n = len(words)
    deletions = most_deletions(n, similarity)
    if n == 0 or deletions < 0:
        return np.zeros(0, np.int64)
    left = {words.tobytes()}
    for d in range(1, min(deletions, n - 1) + 1):
        left.update(np.delete(words, at).tobytes() for at in itertools.combinations(range(n), d))
    return np.array(sorted(xxhash.xxh3_64_intdigest(x, seed=SHORT_EDITS) for x in left), np.uint64).view(np.int64)


SKETCH = "doc_id long, sha binary, n_words int, bins array<tinyint>, buckets array<long>"


def sketches(docs: DataFrame, k: int = SHINGLE, m: int = SKETCHES, least: int = LEAST, seed: int = 11, similarity: float = SIMILARITY) -> DataFrame:
    """The buckets of each text of docs (doc_id, text), with its words counted in bins (127 at most in one)."""

    def task(batches):
        import pyarrow as pa

        multipliers = _multipliers(m, seed)
        known = _Words()
        for batch in slices(batches):
            found, sizes, bins = [], [], []
            for text in batch.column(1).to_pylist():
                words = text.split()
                hashes = word_hashes(words, known)
                found.append(text_buckets(hashes, multipliers, k, least, similarity))
                sizes.append(len(words))
                bins.append(in_bins(hashes))
            offsets_of = np.concatenate([[0], np.cumsum([len(x) for x in found])]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(offsets_of), pa.array(np.concatenate(found or [np.zeros(0, np.int64)])))
            counts = pa.ListArray.from_arrays(pa.array(np.arange(len(bins) + 1, dtype=np.int32) * BINS), pa.array(np.concatenate(bins or [np.zeros(0, np.int8)])))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(sizes, pa.int32()), counts, lists], ["doc_id", "sha", "n_words", "bins", "buckets"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text")).withColumn("sha", F.unhex(F.sha2("text", 256)))
    return rows.mapInArrow(task, SKETCH)


def compare(pairs: DataFrame, texts: DataFrame, similarity: float) -> DataFrame:
    """Aligns pairs (a, b) of nodes: a, b, linked."""

    def task(batches):
        import pyarrow as pa

        for batch in slices(batches):
            out = []
            for a, b, x, y in zip(*(batch.column(i).to_pylist() for i in range(4))):
                x, y = x.split(), y.split()
                limit = limit_of(max(len(x), len(y)), similarity)
                out.append((a, b, bool(x) == bool(y) and edit_distance(x, y, limit) <= limit))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), (pa.int64(), pa.int64(), pa.bool_()))], ["a", "b", "linked"])

    left = texts.select(F.col("node").alias("a"), F.col("text").alias("text_a"))
    right = texts.select(F.col("node").alias("b"), F.col("text").alias("text_b"))
    both = pairs.join(right, "b").join(left, "a").select("a", "b", "text_a", "text_b")
    return both.mapInArrow(task, "a long, b long, linked boolean")


def components(edges: DataFrame) -> DataFrame:
    """node, label: the smallest node of each connected component of edges (a, b). Smallest labels spread over edges and jump along labels."""
    both = edges.select(F.col("a").alias("src"), F.col("b").alias("dst"))
    both = written(both.unionByName(both.select(F.col("dst").alias("src"), F.col("src").alias("dst"))), "component-edges")
    labels = written(both.groupBy(F.col("src").alias("node")).agg(F.least(F.min("dst"), F.col("src")).alias("label")), "component-labels")
    while True:
        near = both.join(labels.select(F.col("node").alias("dst"), "label"), "dst").groupBy(F.col("src").alias("node")).agg(F.min("label").alias("near"))
        spread = labels.join(near, "node").select("node", F.col("label").alias("old"), F.least("label", "near").alias("label"))
        jump = labels.select(F.col("node").alias("label"), F.col("label").alias("further"))
        new = written(spread.join(jump, "label").select("node", "old", F.least("label", "further").alias("label")), "component-labels")
        labels = new.select("node", "label")
        if new.filter("old <> label").isEmpty():
            return labels


def near_classes(docs: DataFrame, similarity: float = SIMILARITY, k: int = SHINGLE, m: int = SKETCHES, least: int = LEAST) -> DataFrame:
    """One row for each row of docs (doc_id, text): doc_id, class_id (the smallest doc_id of the class), class_size, sha."""
    digests = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.unhex(F.sha2(text_or_empty(), 256)).alias("sha"))
    same = [F.any_value(c).alias(c) for c in ("n_words", "bins", "buckets")]
    nodes = sketches(docs, k, m, least, similarity=similarity).groupBy("sha").agg(F.min("doc_id").alias("low"), F.count(F.lit(1)).alias("n"), *same)
    nodes = written(nodes.withColumn("node", F.monotonically_increasing_id()), "near-nodes")
    rows = nodes.select("node", F.explode("buckets").alias("bucket"))
    heads = rows.groupBy("bucket").agg(F.min("node").alias("head"), F.count(F.lit(1)).alias("_n")).filter("_n > 1").drop("_n")
    shared = written(rows.join(heads, "bucket"), "near-buckets")
    texts = node_texts(docs, nodes, shared)
    about = nodes.select("node", "n_words", "bins")
    pairs = shared.filter((F.pmod("bucket", F.lit(STAR_SHARE)) == 0) & (F.col("node") != F.col("head"))).select(F.col("head").alias("a"), F.col("node").alias("b")).distinct()
    compared = written(compare(allowed(pairs, about, similarity), texts, similarity), "near-compared")
    labels = components(compared.filter("linked"))
    seen = mixed_buckets(shared.select("bucket", "node"), labels)
    if not seen.isEmpty():
        more = strays(seen).join(compared.select("a", "b"), ["a", "b"], "left_anti")
        again = written(compare(allowed(more, about, similarity), texts, similarity), "near-compared")
        compared = compared.unionByName(again)
        if not again.filter("linked").isEmpty():
            labels = components(compared.filter("linked"))
            seen = mixed_buckets(seen.select("bucket", "node"), labels)
        more = allowed(pairs_of_light(seen), about, similarity)
        heavy = written(seen.filter(F.col("size") > LIGHT).select("node", "label").distinct().join(texts, "node"), "near-heavy")
        words = rare_words(heavy, similarity)
        if words is not None:
            more = more.unionByName(pairs_of_rare(words.filter("part >= 0"), similarity)).distinct()
        more = more.join(compared.select("a", "b"), ["a", "b"], "left_anti")
        again = written(compare(more, texts, similarity), "near-compared").filter("linked").select("a", "b")
        if words is not None and not (frequent := words.filter("part < 0").select(F.explode("words").alias("bucket"), "node")).isEmpty():
            again = again.unionByName(written(links_of_frequent(mixed_buckets(frequent, labels), texts, similarity), "near-links"))
        if not again.isEmpty():
            labels = components(compared.filter("linked").select("a", "b").unionByName(again))
    named = nodes.select("sha", "node", "low", "n").join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))
    classes = named.groupBy("label").agg(F.min("low").alias("class_id"), F.sum("n").alias("class_size"))
    named = written(named.join(classes, "label").select("sha", "class_id", "class_size"), "near-classes")
    return digests.join(named, "sha").select("doc_id", "class_id", "class_size", "sha")


def may_link(x: str, y: str, similarity: float):
    """Whether the lengths and bins of two texts allow a link. What one text has more of in some bins must all be edited
    away, and what the other has more of in others edited in: the greater of the two sums, (apart + longer) / 2, bounds
    the distance from below."""
    limit = F.floor((1 - similarity) * F.greatest(f"n_words_{x}", f"n_words_{y}") + 1e-9)
    longer = F.abs(F.col(f"n_words_{x}") - F.col(f"n_words_{y}"))
    apart = F.aggregate(F.zip_with(f"bins_{x}", f"bins_{y}", lambda a, b: F.abs(a.cast("int") - b.cast("int"))), F.lit(0), lambda n, d: n + d)
    full = F.array_max(f"bins_{x}").cast("int") == 127
    other = F.array_max(f"bins_{y}").cast("int") == 127
    # Counts stop at 127; where one may have stopped, the lengths say nothing about the bins.
    return (longer <= limit) & (apart + F.when(full | other, 0).otherwise(longer) <= 2 * limit)


def allowed(pairs: DataFrame, about: DataFrame, similarity: float) -> DataFrame:
    """The pairs (a, b) that lengths and bins allow to be links."""
    one, two = (about.select(F.col("node").alias(s), F.col("n_words").alias(f"n_words_{s}"), F.col("bins").alias(f"bins_{s}")) for s in "ab")
    return pairs.join(two, "b").join(one, "a").filter(may_link("a", "b", similarity)).select("a", "b")


def mixed_buckets(shared: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows (bucket, node) of buckets with nodes of several classes: ``common``, the class that most of them have, and ``size``."""
    of = written(shared.join(labels, "node", "left").withColumn("label", F.coalesce("label", "node")), "near-labelled")
    counts = of.groupBy("bucket", "label").agg(F.count(F.lit(1)).alias("n"))
    mixed = counts.groupBy("bucket").agg(F.max(F.struct("n", "label"))["label"].alias("common"), F.sum("n").alias("size"), F.count(F.lit(1)).alias("n")).filter("n > 1").drop("n")
    return written(of.join(mixed, "bucket"), "near-mixed")


def strays(seen: DataFrame) -> DataFrame:
    """Pairs (a, b) of a node of another class than its bucket's common one with the smallest node of that one."""
    first = seen.filter("label = common").groupBy("bucket").agg(F.min("node").alias("y"))
    near = seen.filter("label <> common").select("bucket", F.col("node").alias("x")).join(first, "bucket")
    return near.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()


def pairs_of_light(seen: DataFrame) -> DataFrame:
    """Pairs (a, b) of a small bucket of different classes, one of them not the bucket's common class."""
    light = seen.filter(F.col("size") <= LIGHT)
    one = light.filter("label <> common").select("bucket", F.col("node").alias("x"), F.col("label").alias("label_x"))
    two = light.select(F.col("bucket").alias("_b"), F.col("node").alias("y"), F.col("label").alias("label_y"), F.col("common").alias("common_y"))
    # Two nodes that both are of other classes than the common one meet once.
    once = (F.col("label_y") == F.col("common_y")) | (F.col("x") < F.col("y"))
    near = one.join(two, (F.col("bucket") == F.col("_b")) & (F.col("label_x") != F.col("label_y")) & once)
    return near.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()


def word_counts(heavy: DataFrame) -> np.ndarray:
    """How many of the nodes' words, each with its number of earlier occurrences in the text, each of ``SLOTS`` slots has:
    for each word at least the number of nodes that have it. What tasks and the driver hold is of fixed size."""

    def task(batches):
        import pyarrow as pa

        known, counts = _Words(), np.zeros(SLOTS, np.int32)
        for batch in slices(batches):
            for text in batch.column(0).to_pylist():
                words = labelled_shingles(word_hashes(text.split(), known), 1)
                np.add.at(counts, (words % np.uint64(SLOTS)).astype(np.int64), 1)
        places = [np.flatnonzero(x).astype(np.int32) for x in np.split(counts, SLOT_ROWS)]
        found = [x[at] for x, at in zip(np.split(counts, SLOT_ROWS), places)]
        yield pa.RecordBatch.from_arrays([pa.array(range(SLOT_ROWS), pa.int32()), pa.array([x.tobytes() for x in places]), pa.array([x.tobytes() for x in found])], ["slots", "places", "counts"])

    def total(key, group):
        import pyarrow as pa

        counts = np.zeros(SLOTS // SLOT_ROWS, np.int64)
        for places, found in zip(group.column("places").to_pylist(), group.column("counts").to_pylist()):
            counts[np.frombuffer(places, np.int32)] += np.frombuffer(found, np.int32)
        return pa.table({"slots": pa.array([key[0].as_py()], pa.int32()), "counts": pa.array([np.minimum(counts, (1 << 31) - 1).astype(np.int32).tobytes()])})

    rows = heavy.select("text").mapInArrow(task, "slots int, places binary, counts binary").groupBy("slots").applyInArrow(total, "slots int, counts binary")
    counts = np.zeros((SLOT_ROWS, SLOTS // SLOT_ROWS), np.int32)
    for row in rows.collect():
        counts[row.slots] = np.frombuffer(row.counts, np.int32)
    return counts.ravel()


def rarest(words: np.ndarray, counts: np.ndarray, similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """The words that a text shares one of with each text it links to, and their counts.

    A link of a text of n words leaves at least n - limit_of(n) of them in common, and no fewer if the other is longer.
    So in any order of all words the first limit_of(n) + 1 of both have one in common. One that no other has is left out."""
    count = counts[(words % np.uint64(len(counts))).astype(np.int64)]
    first = np.lexsort((words, count))[: limit_of(len(words), similarity) + 1]
    first = first[count[first] > 1]
    return words[first], count[first]


def rare_words(heavy: DataFrame, similarity: float) -> DataFrame | None:
    """part, node, label, n_words, brief, words, before, about: the rarest words of each node, by the task in which they meet
    (-1: words that more than ``FREQUENT`` nodes may have), with the first ``BEFORE`` words of earlier tasks; None if there is no
    node. ``brief`` is what each task gets of a node's bins; ``about``, its bins and bits, compressed, is in one row of the node
    only. Bins count labelled words, so that a word that a text repeats doesn't fill one."""
    counts, columns = word_counts(heavy), ["part", "node", "label", "n_words", "brief", "words", "before", "about"]
    if not counts.any():
        return None
    parts = 1 + int((1 - similarity) * counts.sum(dtype=np.int64)) // PART_WORDS

    def task(batches):
        import pyarrow as pa

        known = _Words()
        for batch in slices(batches):
            at, part, sizes, brief, words, before, about = [], [], [], [], [], [], []
            for k, text in enumerate(batch.column(2).to_pylist()):
                hashes = word_hashes(text.split(), known)
                labelled = labelled_shingles(hashes, 1)
                found, count = rarest(labelled, counts, similarity)
                bins = in_bins(labelled)
                of = np.where(count > FREQUENT, -1, ((found >> np.uint64(32)) % np.uint64(parts)).astype(np.int64))
                order = np.lexsort((found, of))
                found, of = found[order].view(np.int64), of[order]
                own = int(np.searchsorted(of, 0))
                for p in np.unique(of).tolist():
                    first, last = np.searchsorted(of, [p, p + 1])
                    at.append(k)
                    part.append(p)
                    sizes.append(len(hashes))
                    brief.append(in_brief(bins))
                    words.append(found[first:last])
                    before.append(found[own : min(first, own + BEFORE)])
                    about.append(zlib.compress(bins.tobytes() + in_bits(labelled).tobytes(), 1) if first == own and p >= 0 else None)
            if at:
                lists = [pa.ListArray.from_arrays(pa.array(np.cumsum([0] + [len(x) for x in of]).astype(np.int32)), pa.array(np.concatenate(of))) for of in (words, before)]
                own = [batch.column(i).take(pa.array(at)) for i in (0, 1)]
                yield pa.RecordBatch.from_arrays([pa.array(part, pa.int32()), *own, pa.array(sizes, pa.int32()), pa.array(brief, pa.binary()), *lists, pa.array(about, pa.binary())], columns)

    return written(heavy.select("node", "label", "text").mapInArrow(task, "part int, node long, label long, n_words int, brief binary, words array<long>, before array<long>, about binary"), "near-words")


def pairs_of_rare(words: DataFrame, similarity: float) -> DataFrame:
    """Pairs (a, b) of nodes of different classes with a rare word in common that lengths, bins and bits allow to be links. A pair
    may come from several tasks of words, if it has a word of an earlier one in common, but none of the first ``BEFORE``; it is given once."""

    def task(group):
        import pyarrow as pa

        node, label, n_words = (np.asarray(group.column(c)) for c in ("node", "label", "n_words"))
        bins = from_brief(np.frombuffer(b"".join(group.column("brief").to_pylist()), np.uint8).reshape(len(node), -1))
        lists = group.column("words").combine_chunks()
        owner = np.repeat(np.arange(len(node)), lists.value_lengths().to_numpy(zero_copy_only=False))
        found = list(rare_pairs(owner, lists.flatten().to_numpy(zero_copy_only=False), label, n_words.astype(np.int64), bins, similarity, group.column("before"), BRIEF_MOST))
        pairs = np.concatenate(found or [np.zeros((0, 2), np.int64)])
        if group.nbytes > 1 << 20:
            released()
        x, y = node[pairs[:, 0]], node[pairs[:, 1]]
        return pa.table({"a": pa.array(np.minimum(x, y), pa.int64()), "b": pa.array(np.maximum(x, y), pa.int64())})

    met = words.select("part", "node", "label", "n_words", "brief", "words", "before").groupBy("part").applyInArrow(task, "a long, b long")
    about = words.filter("about IS NOT NULL").select("node", "n_words", "about")
    return closely_allowed(written(met.distinct(), "near-met"), about, similarity)


def closely_allowed(pairs: DataFrame, about: DataFrame, similarity: float) -> DataFrame:
    """The pairs (a, b) that lengths, all bins and bits allow to be links. What is known of a node goes once to each task that
    has pairs of it, not with each pair."""
    parts = 1 + pairs.count() // PART_CHECKED
    pairs = pairs.withColumn("part", F.pmod(F.xxhash64("a"), F.lit(parts)).cast("int"))
    nodes = pairs.select(F.col("part").alias("of"), F.explode(F.array("a", "b")).alias("node")).distinct().join(about, "node")

    def task(pairs, nodes):
        import pyarrow as pa

        node, n_words, about = np.asarray(nodes.column("node")), np.asarray(nodes.column("n_words")).astype(np.int64), nodes.column("about")
        order, kept = np.argsort(node), []
        ends = np.stack([np.asarray(pairs.column(c)) for c in "ab"], 1)
        ends = ends[np.argsort(ends[:, 0], kind="stable")]
        for start in range(0, len(ends), 1 << 12):
            block = ends[start : start + (1 << 12)]
            own, at = np.unique(order[np.searchsorted(node, block, sorter=order)], return_inverse=True)
            bins, bits = np.empty((len(own), BINS), np.int8), np.empty((len(own), BITS // 64), np.uint64)
            for k, of in enumerate(own.tolist()):
                unpacked = zlib.decompress(about[of].as_py())
                bins[k], bits[k] = np.frombuffer(unpacked, np.int8, BINS), np.frombuffer(unpacked, np.uint64, offset=BINS)
            kept.append(block[closely(at.reshape(-1, 2), n_words[own], bins, bits, similarity)])
        if nodes.nbytes > 1 << 20:
            released()
        kept = np.concatenate(kept or [np.zeros((0, 2), np.int64)])
        return pa.table({"a": pa.array(kept[:, 0], pa.int64()), "b": pa.array(kept[:, 1], pa.int64())})

    return pairs.groupBy("part").cogroup(nodes.groupBy("of")).applyInArrow(task, "a long, b long")


def closely(pairs: np.ndarray, sizes: np.ndarray, bins: np.ndarray, bits: np.ndarray, similarity: float) -> np.ndarray:
    """Which pairs of rows lengths, bins and bits allow to be links."""
    x, y = pairs[:, 0], pairs[:, 1]
    x, y = np.where(sizes[x] > sizes[y], y, x), np.where(sizes[x] > sizes[y], x, y)
    limit, longer = np.floor((1 - similarity) * sizes[y] + 1e-9).astype(np.int64), sizes[y] - sizes[x]
    stopped = bins.max(axis=1, initial=0) == 127
    apart = np.abs(bins[x].astype(np.int16) - bins[y]).sum(axis=1, dtype=np.int64)
    near = (longer <= limit) & (apart + np.where(stopped[x] | stopped[y], 0, longer) <= 2 * limit)
    some = np.flatnonzero(near)
    x_bits, y_bits = bits[x[some]], bits[y[some]]
    # A bit of one text only is a word of its own at least; the longer text has as many more as it is longer.
    of_x = np.bitwise_count(x_bits & ~y_bits).sum(axis=1, dtype=np.int64) + longer[some]
    of_y = np.bitwise_count(y_bits & ~x_bits).sum(axis=1, dtype=np.int64)
    near[some] = np.maximum(of_x, of_y) <= limit[some]
    return near


def rare_pairs(owner: np.ndarray, words: np.ndarray, label: np.ndarray, n_words: np.ndarray, bins: np.ndarray, similarity: float, before: Iterable | None = None, most: int = 127) -> Iterable[np.ndarray]:
    """Arrays of pairs (x, y) of nodes of different labels that have one of ``words`` (of the nodes ``owner``) in common, by
    the bounds of ``may_link``, with ``most`` words at most counted in a bin; each pair once, and none that has a word of its
    lists in ``before`` in common."""
    by_size = np.argsort(n_words, kind="stable")
    rank = np.argsort(by_size)
    label, sizes, bins = label[by_size], n_words[by_size], bins[by_size]
    limit = np.floor((1 - similarity) * sizes + 1e-9).astype(np.int64)
    stopped = bins.max(axis=1, initial=0) == most
    at = rank[owner]
    order = np.lexsort((at, words))
    at, words = at[order], words[order]
    cuts = np.flatnonzero(np.concatenate([[True], words[1:] != words[:-1], [True]])) if len(words) else np.zeros(1, np.int64)
    held, n_held, given, earlier = [], 0, np.zeros(0, np.int64), {}

    def earlier_words(node: int) -> set:
        if node not in earlier:
            earlier[node] = set(before[node].as_py())
        return earlier[node]

    def allowed_pairs():
        nonlocal given
        code, passed = np.setdiff1d(np.concatenate(held), given), []
        for start in range(0, len(code), 1 << 12):
            x, y = np.divmod(code[start : start + (1 << 12)], len(sizes))
            apart = np.abs(bins[x].astype(np.int16) - bins[y]).sum(axis=1, dtype=np.int64)
            near = apart + np.where(stopped[x] | stopped[y], 0, sizes[y] - sizes[x]) <= 2 * limit[y]
            pairs = np.stack([by_size[x[near]], by_size[y[near]]], 1)
            passed.append(code[start : start + (1 << 12)][near])
            if before is not None:
                pairs = pairs[np.fromiter((earlier_words(a).isdisjoint(earlier_words(b)) for a, b in pairs.tolist()), bool, len(pairs))]
            yield pairs
        given = np.concatenate([given, *passed])

    several = np.flatnonzero(np.diff(cuts) > 1)
    for low, high in zip(cuts[several].tolist(), cuts[several + 1].tolist()):
        group = at[low:high]
        labels = label[group]
        if (labels == labels[0]).all():
            continue
        # Of two nodes the later one is as long or longer; the least length that it can link to grows with its own.
        least = sizes[group] - limit[group]
        for start in range(0, len(group), 256):
            x = group[start : start + 256]
            end = int(np.searchsorted(least, sizes[x[-1]], "right"))
            y = group[start:end]
            i, j = np.nonzero((labels[start : start + 256, None] != labels[None, start:end]) & (least[None, start:end] <= sizes[x][:, None]) & (x[:, None] < y[None]))
            held.append(x[i] * len(sizes) + y[j])
            n_held += len(i)
            if n_held >= PART_PAIRS:
                yield from allowed_pairs()
                held, n_held = [], 0
    if held:
        yield from allowed_pairs()


def links_of_frequent(heavy: DataFrame, texts: DataFrame, similarity: float) -> DataFrame:
    """Links (a, b) between the classes of each frequent word, a bucket here: enough to join what any link of it joins."""
    nodes = heavy.groupBy("node").agg(F.any_value("label").alias("label"), F.array_sort(F.collect_list("bucket")).alias("heavy")).join(texts, "node")
    rows = written(nodes.withColumn("n_bytes", F.octet_length("text").cast("long")), "near-frequent").withColumn("bucket", F.explode("heavy"))
    blocks = F.greatest(F.ceil(F.count(F.lit(1)) / BLOCK_NODES), F.ceil(F.sum("n_bytes") / BLOCK_BYTES)).cast("int")
    sizes = rows.groupBy("bucket").agg(blocks.alias("blocks")).join(heavy.groupBy("bucket").agg(F.any_value("common").alias("common")), "bucket")
    rows = rows.join(sizes, "bucket")
    rows = rows.withColumn("own", F.pmod(F.xxhash64("node"), "blocks").cast("int")).withColumn("other", F.explode(met_by("own", "blocks")))
    rows = rows.withColumn("i", F.least("own", "other")).withColumn("j", F.greatest("own", "other"))

    def task(key, group):
        import pyarrow as pa

        bucket, i, j = (x.as_py() for x in key)
        common = group.column("common")[0].as_py()
        own, nodes, labels = (np.asarray(group.column(c)) for c in ("own", "node", "label"))
        within = [own == k for k, other in ((i, j), (j, i)) if i != j and (k + 1) % group.column("blocks")[0].as_py() == other]
        found = linked_nodes(bucket, common, own == i, own == j, nodes, labels, group.column("heavy").to_pylist(), map(lambda x: x.as_py(), group.column("text")), similarity, within)
        if group.nbytes > 1 << 20:
            released()
        return pa.table({"a": pa.array([a for a, _ in found], pa.int64()), "b": pa.array([b for _, b in found], pa.int64())})

    columns = ["bucket", "blocks", "i", "j", "own", "common", "node", "label", "heavy", "text"]
    return rows.select(*columns).groupBy("bucket", "i", "j").applyInArrow(task, "a long, b long").distinct()


def met_by(own: str, blocks: str) -> Column:
    """The blocks whose nodes meet those of block ``own`` in tasks of two. The nodes of a block meet each other in the task
    that it shares with the next one, so only a bucket of one block has a task of one."""
    return F.filter(F.sequence(F.lit(0), F.col(blocks) - 1), lambda k: (k != F.col(own)) | (F.col(blocks) == 1))


def linked_nodes(bucket: int, common: int, left: np.ndarray, right: np.ndarray, nodes: np.ndarray, labels: np.ndarray, heavy: list, texts: Iterable[str], similarity: float, within: list | tuple = ()) -> list:
    """Links between nodes marked ``left`` and nodes marked ``right`` of different classes, and among the nodes of each mark
    ``within``, but for links between nodes that earlier ones join."""
    # Each word is a number, so that a block's texts take four bytes a word instead of a string.
    numbers: dict = {}
    words = []
    for text in texts:
        w = text.split()
        words.append(np.fromiter((numbers.setdefault(x, len(numbers)) for x in w), np.int32, len(w)))
    sizes = np.array([len(w) for w in words])
    bin_of = np.fromiter((xxhash.xxh3_64_intdigest(x.encode("utf-8", "surrogatepass")) % BLOCK_BINS for x in numbers), np.int64, len(numbers))
    del numbers
    bins = np.zeros((len(words), BLOCK_BINS), np.int16)
    for at, w in enumerate(words):
        bins[at] = np.minimum(np.bincount(bin_of[w], minlength=BLOCK_BINS), 32767)
    stopped = bins.max(axis=1, initial=0) == 32767
    # Which earlier buckets each node is in: a pair is left to the first bucket that both share.
    earlier = {b: k for k, b in enumerate(sorted({b for h in heavy for b in h if b < bucket}))}
    inside = np.zeros((len(words), max(len(earlier), 1)), np.float32)
    for at, h in enumerate(heavy):
        inside[at, [earlier[b] for b in h if b < bucket]] = 1
    root: dict = {}

    def class_of(label: int) -> int:
        while (up := root.get(label, label)) != label:
            root[label] = root.get(up, up)
            label = up
        return label

    links = []
    same = bool(np.array_equal(left, right))
    for these, those in [(m, m) for m in within] + [(left, right)] + [(right, left)] * (not same):
        others = np.flatnonzero(those)
        theirs, their_bins, their_sizes, their_stop, their_inside = labels[others], bins[others], sizes[others], stopped[others], inside[others]
        for x in np.flatnonzero(these & (labels != common)):
            limit = np.floor((1 - similarity) * np.maximum(their_sizes, sizes[x]) + 1e-9).astype(np.int64)
            longer = np.abs(their_sizes - sizes[x])
            # Two nodes that both are of other classes than the common one meet once.
            may = (theirs != labels[x]) & (longer <= limit) & ((theirs == common) | (nodes[others] > nodes[x])) & ((their_sizes > 0) == (sizes[x] > 0))
            may = np.flatnonzero(may & (their_inside @ inside[x] == 0))
            if not len(may):
                continue
            apart = np.abs(their_bins[may] - bins[x]).sum(axis=1, dtype=np.int64)
            bound = apart + np.where(their_stop[may] | stopped[x], 0, longer[may])
            near = bound <= 2 * limit[may]
            may, apart = may[near], apart[near]
            own = words[x].tolist() if len(may) else []
            for y in may[np.argsort(apart, kind="stable")]:
                at = others[y]
                if class_of(int(labels[x])) == class_of(int(labels[at])):
                    continue
                if edit_distance(own, words[at].tolist(), int(limit[y])) <= limit[y]:
                    root[class_of(int(labels[x]))] = class_of(int(labels[at]))
                    links.append((int(min(nodes[x], nodes[at])), int(max(nodes[x], nodes[at]))))
    return links


def node_texts(docs: DataFrame, nodes: DataFrame, rows: DataFrame) -> DataFrame:
    """node, text of the nodes that share a bucket with another; other texts aren't moved."""
    wanted = written(nodes.join(rows.select("node").distinct(), "node", "left_semi").select("node", "sha"), "near-wanted")
    texts = docs.select(text_or_empty().alias("text")).withColumn("sha", F.unhex(F.sha2("text", 256)))
    texts = KeyFilter(wanted, "sha").prune(texts, "sha").groupBy("sha").agg(F.min("text").alias("text"))
    return written(texts.join(wanted, "sha").select("node", "text"), "near-texts")


def keep_one(docs: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """The rows of docs that stay: of each class the row with the smallest (doc_id, text)."""
    found = near_classes(docs, similarity)
    # Rows of one class; the class's row is named by its id and the digest of its text.
    best = written(found.groupBy("class_id").agg(F.min(F.struct("doc_id", "sha")).alias("best")).select("best.doc_id", "best.sha").distinct(), "near-kept")
    kept = best.select(F.col("doc_id").alias("_doc"), F.col("sha").alias("_sha"))
    rows = docs.withColumn("_own", F.unhex(F.sha2(text_or_empty(), 256)))
    rows = rows.join(kept, F.col("doc_id").cast("long").eqNullSafe(F.col("_doc")) & (F.col("_own") == F.col("_sha")), "left_semi")
    return rows.drop("_own")
