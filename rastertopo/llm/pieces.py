"""SentencePiece encoding and decoding as a weighted finite-state transducer.

Three machines are compiled from a model file: the normaliser (rewriting rules, the dummy prefix, blanks written as
the meta symbol), the lexicon (a trie of the pieces whose ends return to the start, weighted by the negated scores) and
the byte fallback (characters outside the lexicon to their UTF-8 bytes). Encoding composes them with the input on the
fly and takes the shortest path in the tropical semiring.

In a unigram model every piece may follow every other, so that path is the likeliest segmentation. In a byte-pair
model the score is the rank of a merge, not a likelihood: there an arc for piece b after piece a has weight infinity
unless merging the characters of a and b by rank gives exactly a, b. Exactly one path is then finite, and it is the
segmentation that the merges give; so the same search serves both kinds.

No piece holds a blank after another character, so the lattice has a single state before each run of blanks: the
input is cut there and the paths of equal parts are computed once.

Cases: null and empty texts give no tokens; characters outside the lexicon become bytes, or the unknown token where
the model has no bytes; a repeated row is encoded like the first; an empty table gives an empty result; existing
columns stay, and those named like a result are replaced.
"""

from __future__ import annotations

import hashlib
import re
import struct
from itertools import chain
from math import inf

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BooleanType, IntegerType, StringType, StructField, StructType

from .common import slices, worker_state

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
BLANK = "▁"
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
UNIGRAM, BPE = 1, 2
UNKNOWN_SURFACE = " ⁇ "
CACHED_PARTS, LONGEST_CACHED, CACHED_PAIRS = 300_000, 48, 500_000


def _fields(data: bytes):
    """The (number, value) fields of a protocol buffer message."""
    at = 0

    def varint() -> int:
        nonlocal at
        value = shift = 0
        while True:
            byte = data[at]
            at += 1
            value |= (byte & 127) << shift
            shift += 7
            if byte < 128:
                return value

    while at < len(data):
        key = varint()
        kind = key & 7
        if kind == 0:
            yield key >> 3, varint()
        elif kind == 2:
            size = varint()
            yield key >> 3, data[at : at + size]
            at += size
        elif kind == 5:
            yield key >> 3, struct.unpack("<f", data[at : at + 4])[0]
            at += 4
        else:
            yield key >> 3, data[at : at + 8]
            at += 8


class Normaliser:
    """The first machine: rules rewrite the longest match at each place, then blanks become the meta symbol."""

    def __init__(self, dummy_prefix: bool = True, strip: bool = False, escape: bool = True, rules: dict[str, str] | None = None):
        self.dummy_prefix, self.strip, self.escape = dummy_prefix, strip, escape
        self.rules = dict(rules or {})
        self.match = re.compile("|".join(map(re.escape, sorted(self.rules, key=len, reverse=True)))) if self.rules else None

    def __call__(self, text: str) -> str:
        if self.match:
            text = self.match.sub(lambda m: self.rules[m[0]], text)
        if self.strip:
            text = re.sub(" +", " ", text).strip(" ")
        if not text:
            return ""
        if self.dummy_prefix:
            text = " " + text
        return text.replace(" ", BLANK) if self.escape else text


class _Parts(dict):
    """The cache of a model's parts; it finds what it lacks."""

    def __init__(self, model: PieceModel):
        self.model = model

    def __missing__(self, part: str) -> tuple[int, ...]:
        return self.model.part_ids(part)


class PieceModel:
    """A compiled model; ``encode`` and ``decode`` of single texts."""

    def __init__(self, data: bytes, kind: int | None = None):
        self.pieces, self.scores, self.kinds = [], [], []
        self.kind, dummy, strip, escape, charsmap = UNIGRAM, True, True, True, b""
        for number, value in _fields(data):
            if number == 1:
                piece = dict(_fields(value))
                self.pieces.append(piece.get(1, b"").decode())
                self.scores.append(piece.get(2, 0.0))
                self.kinds.append(piece.get(3, NORMAL))
            elif number == 2:
                self.kind = dict(_fields(value)).get(3, UNIGRAM)
            elif number == 3:
                spec = dict(_fields(value))
                dummy, strip, escape, charsmap = bool(spec.get(3, 1)), bool(spec.get(4, 1)), bool(spec.get(5, 1)), spec.get(2, b"")
        if charsmap:
            raise ValueError("models with a compiled character map aren't supported: give its rules to a Normaliser")
        self.kind = kind or self.kind
        if self.kind not in (UNIGRAM, BPE):
            raise ValueError("only unigram and byte-pair models are supported")
        self.normalise = Normaliser(dummy, strip, escape)
        self.unknown = self.kinds.index(UNKNOWN)
        self.ids = {p: i for i, (p, k) in enumerate(zip(self.pieces, self.kinds)) if k in (NORMAL, USER)}
        self.bytes = [self.pieces.index(f"<0x{b:02X}>") for b in range(256)] if BYTE in self.kinds else None
        self.byte_of = {i: b for b, i in enumerate(self.bytes or ())}
        normal = [self.scores[i] for i in self.ids.values() if self.kinds[i] == NORMAL]
        self.unknown_cost = -(min(normal, default=0.0) - 10.0)
        best = max(normal, default=0.0)
        self.trie: dict = {}
        for piece, i in self.ids.items():
            node = self.trie
            for c in piece:
                node = node.setdefault(c, {})
            # User symbols always win over other paths.
            node[""] = (i, -self.scores[i] if self.kinds[i] == NORMAL else -(len(piece) * best - 0.1))
        users = sorted((p for p in self.ids if self.kinds[self.ids[p]] == USER), key=len, reverse=True)
        self.users = re.compile("(" + "|".join(map(re.escape, users)) + ")") if users and self.kind == BPE else None
        late = any(BLANK in p.lstrip(BLANK) for p in self.ids)
        line = any("\n" in p and len(p) > 1 for p in self.ids)
        self.parts = re.compile("(?s:.+)" if late else f"{BLANK}*[^{BLANK}]+|{BLANK}+" if line else f"{BLANK}*[^{BLANK}\n]+|{BLANK}+|\n")
        self.follows: dict[int, bool] = {}
        self.cache = _Parts(self)
        # What a token alone decodes to; none where its neighbours matter.
        self.surface: list[str | None] = [p.replace(BLANK, " ") if k not in (CONTROL, UNKNOWN, BYTE) else None for p, k in zip(self.pieces, self.kinds)]
        for i, b in self.byte_of.items():
            if b < 128:
                self.surface[i] = chr(b)

    def merged(self, text: str) -> list[str]:
        """The characters of ``text`` merged by rank: the best scored pair first, of equal ones the leftmost."""
        parts = list(text)
        while True:
            best, place = -inf, -1
            for k in range(len(parts) - 1):
                i = self.ids.get(parts[k] + parts[k + 1])
                if i is not None and self.scores[i] > best:
                    best, place = self.scores[i], k
            if place < 0:
                return parts
            parts[place : place + 2] = [parts[place] + parts[place + 1]]

    def may_follow(self, a: int, b: int) -> bool:
        key = a << 20 | b
        found = self.follows.get(key)
        if found is None:
            found = self.follows[key] = self.merged(self.pieces[a] + self.pieces[b]) == [self.pieces[a], self.pieces[b]]
        return found

    def shortest(self, part: str) -> tuple[int, ...]:
        """Piece ids of the shortest path over a normalised part; unknown characters are -1 - their place."""
        return self._only_path(part) if self.kind == BPE else self._cheapest_path(part)

    def _arcs(self, part: str, i: int) -> list[tuple[int, int, float]]:
        """The arcs that leave place i, shortest first: (place after, piece, weight)."""
        node, arcs = self.trie, []
        for j in range(i, len(part)):
            node = node.get(part[j])
            if node is None:
                break
            arc = node.get("")
            if arc is not None:
                arcs.append((j + 1, *arc))
        if not arcs or arcs[0][0] != i + 1:
            arcs.insert(0, (i + 1, -1 - i, self.unknown_cost))
        return arcs

    def _cheapest_path(self, part: str) -> tuple[int, ...]:
        n = len(part)
        cost, last, back = [inf] * (n + 1), [-1] * (n + 1), [0] * (n + 1)
        cost[0] = 0.0
        for i in range(n):
            here = cost[i]
            for j, piece, weight in self._arcs(part, i):
                if here + weight < cost[j]:
                    cost[j], last[j], back[j] = here + weight, piece, i
        path, j = [], n
        while j:
            path.append(last[j])
            j = back[j]
        return tuple(reversed(path))

    def _only_path(self, part: str) -> tuple[int, ...]:
        """The one path of finite weight, searched depth first along the longest arcs. The finite path to a place is
        unique, so a place from which the end can't be reached is left for good."""
        n, trie, follows = len(part), self.trie, self.follows
        path, places, pending, dead = [], [0], [], set()
        i, before = 0, -1
        while i < n:
            node, arcs = trie, []
            for j in range(i, n):
                node = node.get(part[j])
                if node is None:
                    break
                arc = node.get("")
                if arc is not None:
                    arcs.append((j + 1, arc[0]))
            if not arcs or arcs[0][0] != i + 1:
                arcs.insert(0, (i + 1, -1 - i))
            while True:
                end = 0
                while arcs:
                    end, piece = arcs.pop()
                    if end in dead:
                        end = 0
                        continue
                    if before < 0 or piece < 0:
                        break
                    ok = follows.get(before << 20 | piece)
                    if self.may_follow(before, piece) if ok is None else ok:
                        break
                    end = 0
                if end:
                    break
                dead.add(i)
                path.pop()
                places.pop()
                arcs = pending.pop()
                i, before = places[-1], path[-1] if path else -1
            pending.append(arcs)
            path.append(piece)
            places.append(end)
            i, before = end, piece
        return tuple(path)

    def part_ids(self, part: str) -> tuple[int, ...]:
        """The ids of a part that isn't cached."""
        if len(self.follows) > CACHED_PAIRS:
            self.follows.clear()
        path = self.shortest(part)
        if min(path) < 0:
            out: list[int] = []
            for i in path:
                if i >= 0:
                    out.append(i)
                elif self.bytes:
                    out += [self.bytes[b] for b in part[-1 - i].encode("utf-8", "surrogatepass")]
                else:
                    out.append(self.unknown)
            path = tuple(out)
        if len(part) <= LONGEST_CACHED:
            if len(self.cache) >= CACHED_PARTS:
                self.cache.clear()
            self.cache[part] = path
        return path

    def encode(self, text: str | None) -> list[int]:
        normal = self.normalise(text) if text else ""
        out: list[int] = []
        for k, piece in enumerate(self.users.split(normal) if self.users else (normal,)):
            if k % 2:
                out.append(self.ids[piece])
            else:
                out.extend(chain.from_iterable(map(self.cache.__getitem__, self.parts.findall(piece))))
        if not self.bytes:  # unknown characters in a row are one token
            out = [i for k, i in enumerate(out) if i != self.unknown or k == 0 or out[k - 1] != self.unknown]
        return out

    def decode(self, ids) -> str:
        if ids is None or len(ids) == 0:
            return ""
        text = list(map(self.surface.__getitem__, ids))
        if None in text:
            pieces, kinds, raw, text = self.pieces, self.kinds, bytearray(), []
            for i in ids:
                if kinds[i] == BYTE:
                    raw.append(self.byte_of[i])
                    continue
                if raw:
                    text.append(raw.decode("utf-8", "replace"))
                    raw = bytearray()
                text.append("" if kinds[i] == CONTROL else UNKNOWN_SURFACE if kinds[i] == UNKNOWN else pieces[i].replace(BLANK, " "))
            text.append(raw.decode("utf-8", "replace"))
        out = "".join(text)
        return out[1:] if self.normalise.dummy_prefix and out.startswith(" ") else out


def read_model(path: str = MODEL) -> bytes:
    """The model file, read on the driver; executors get its bytes (under a megabyte)."""
    with open(path, "rb") as file:
        return file.read()


def _compiled(data: bytes) -> PieceModel:
    """The compiled model of this worker, with what it has cached in earlier tasks."""
    state, key = worker_state(), f"pieces-{hashlib.sha256(data).hexdigest()}"
    if key not in state:
        state[key] = PieceModel(data)
    return state[key]


def _append(batch, names: list[str], arrays: list):
    import pyarrow as pa

    kept = [(n, c) for n, c in zip(batch.schema.names, batch.columns) if n not in names]
    return pa.RecordBatch.from_arrays([c for _, c in kept] + arrays, names=[n for n, _ in kept] + names)


def encode(docs: DataFrame, text_col: str = "text", model: bytes | None = None, keep_text: bool = True, check: bool = False) -> DataFrame:
    """Adds ``ids`` array<int>; with ``check`` also ``decoded`` and ``exact``: whether decoding gives the text again.

    Texts that hold the meta symbol itself decode to a blank there."""
    shipped = docs.sparkSession.sparkContext.broadcast(model or read_model())
    source = docs.columns.index(text_col)
    names = ["ids", "decoded", "exact"] if check else ["ids"]
    drop = names + ([] if keep_text else [text_col])
    added = [StructField("ids", ArrayType(IntegerType(), False)), StructField("decoded", StringType()), StructField("exact", BooleanType())][: len(names)]
    schema = StructType([f for f in docs.schema.fields if f.name not in drop] + added)

    def task(batches):
        import numpy as np
        import pyarrow as pa

        machine = _compiled(shipped.value)
        for batch in slices(batches):
            texts = batch.column(source).to_pylist()
            ids = [machine.encode(x) for x in texts]
            offsets = np.concatenate([[0], np.cumsum([len(x) for x in ids])]).astype(np.int32)
            flat = np.fromiter((i for x in ids for i in x), np.int32, offsets[-1])
            arrays = [pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat))]
            if check:
                decoded = [machine.decode(x) for x in ids]
                arrays += [pa.array(decoded, pa.string()), pa.array([a == (b or "").replace(BLANK, " ") for a, b in zip(decoded, texts)])]
            if not keep_text:
                batch = batch.drop_columns([text_col])
            yield _append(batch, names, arrays)

    return docs.mapInArrow(task, schema)


def decode(rows: DataFrame, ids_col: str = "ids", model: bytes | None = None) -> DataFrame:
    """Adds ``decoded`` to rows with token ids."""
    shipped = rows.sparkSession.sparkContext.broadcast(model or read_model())
    source = rows.columns.index(ids_col)
    schema = StructType([f for f in rows.schema.fields if f.name != "decoded"] + [StructField("decoded", StringType())])

    def task(batches):
        import pyarrow as pa

        machine = _compiled(shipped.value)
        for batch in slices(batches):
            yield _append(batch, ["decoded"], [pa.array([machine.decode(x) for x in batch.column(source).to_pylist()], pa.string())])

    return rows.mapInArrow(task, schema)


def tokens(docs: DataFrame, model: bytes | None = None) -> DataFrame:
    """One row for each document: doc_id, n_tokens, ids, decoded_sha256, exact."""
    found = encode(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), model=model, keep_text=False, check=True)
    return found.select("doc_id", F.size("ids").cast("long").alias("n_tokens"), "ids", F.sha2("decoded", 256).alias("decoded_sha256"), "exact")
