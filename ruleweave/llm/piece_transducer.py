"""SentencePiece encoding and decoding by weighted finite-state transducers (op7).

Four machines are compiled from the model file into arrays:
- the normaliser reads characters and writes those of pieces (blank to U+2581, a leading U+2581 once a text, further blanks dropped
  where the model says so);
- the lexicon, a trie as (state, character) -> state arcs; a final state writes a piece, its weight is the piece's negative score;
- byte fallback, an arc for each character that is no piece, to the ids of its bytes;
- the grammar, whose state is the last piece. For unigram models it has one state and no weights. For byte-pair models the weight from piece
  a to piece b is 0 if merging leaves the border between them and infinite if not: a sequence of pieces is the merged form of its
  text if and only if every two neighbours are, so exactly one path stays finite. Its arcs are computed when first asked for and kept.

Many words are composed with the machines at once: all arcs of all words come from walking the trie from every character, and weights
are relaxed in the tropical semiring (min, +), end position by end position. A prefix has one best path, so a position keeps that path's weight and last
piece only; of equal weights the longer last piece counts. Nothing crosses blanks, so each distinct word is composed once while it stays cached.

Null texts count as empty and have no ids. Decoding gives the normalised text back, with U+2581 as a blank.
"""

from __future__ import annotations

import struct
import zlib
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleweave.llm.common import lean, small_batches

BLANK = "▁"
CACHE_WORDS, CACHE_PAIRS, LONG_WORD, TOGETHER = 150_000, 1_000_000, 64, 256
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
NEVER = 1 << 60


def _fields(raw: bytes):
    """(number, value) of each field of a serialized message."""

    def varint(i):
        value = shift = 0
        while True:
            byte = raw[i]
            value |= (byte & 127) << shift
            i, shift = i + 1, shift + 7
            if byte < 128:
                return value, i

    i = 0
    while i < len(raw):
        tag, i = varint(i)
        if tag & 7 == 0:
            value, i = varint(i)
        elif tag & 7 == 2:
            size, i = varint(i)
            value, i = raw[i : i + size], i + size
        else:
            size = 4 if tag & 7 == 5 else 8
            value, i = struct.unpack("<f" if size == 4 else "<d", raw[i : i + size])[0], i + size
        yield tag >> 3, value


def _find(table: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """The place of each key in a sorted table, -1 where it is not there."""
    at = np.searchsorted(table, keys)
    at[at == len(table)] = 0
    return np.where(table[at] == keys, at, -1) if len(table) else np.full(len(keys), -1)


@dataclass
class Machines:
    """The compiled transducers: plain tables, a few MB, bounded by the vocabulary."""

    pieces: list[str]
    lexicon: dict[str, int]
    byte_ids: list[int]
    inner: set[str]
    bpe: bool
    spaces: str  # what the normaliser does with blanks: "keep" or "collapse"
    runs: dict[int, int]
    arc_keys: np.ndarray  # lexicon: state << 21 | character, sorted
    arc_to: np.ndarray
    final: np.ndarray  # the piece a state writes, -1 for none
    weight: np.ndarray  # of each piece
    unknown: float  # weight of byte fallback
    rank: np.ndarray  # when merging makes a piece, -1 for single characters
    left: np.ndarray
    right: np.ndarray
    join_keys: np.ndarray  # grammar: a << 32 | b of pieces that together are a piece, sorted
    join_rank: np.ndarray
    pair_keys: np.ndarray = field(default_factory=lambda: np.empty(0, np.int64))  # grammar arcs known so far
    pair_stays: np.ndarray = field(default_factory=lambda: np.empty(0, bool))

    def _stays(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Whether byte-pair merging leaves the border between pieces a and b.

        Their merges are undone, latest first. At each step a join across the border must not have come earlier than the merge just undone; of two
        equal merges the left one comes first.
        """
        out = np.zeros(len(a), bool)
        rows, before = np.arange(len(a)), np.full(len(a), NEVER)
        while len(rows):
            at = _find(self.join_keys, a << 32 | b)
            joins = (at >= 0) & (self.join_rank[at] < before) if len(self.join_keys) else np.zeros(len(a), bool)
            ra, rb = self.rank[a], self.rank[b]
            done = ~joins & (ra < 0) & (rb < 0)
            out[rows[done]] = True
            go = ~joins & ~done
            rows, a, b, ra, rb = rows[go], a[go], b[go], ra[go], rb[go]
            of_a = ra > rb
            before = np.where(of_a, ra, rb + 1)
            a, b = np.where(of_a, self.right[a], a), np.where(of_a, b, self.left[b])
        return out

    def follows(self, a: np.ndarray, b: np.ndarray, fresh: list) -> np.ndarray:
        """Grammar arcs from pieces a to pieces b that are finite; those not known yet go to fresh. Byte fallback (-1) meets anything."""
        out = np.ones(len(a), bool)
        real = np.flatnonzero((a >= 0) & (b >= 0))
        keys = a[real] << 32 | b[real]
        at = _find(self.pair_keys, keys)
        stays = self.pair_stays[at] if len(self.pair_keys) else np.zeros(len(keys), bool)
        lost = np.flatnonzero(at < 0)
        if len(lost):
            new, inverse = np.unique(keys[lost], return_inverse=True)
            found = self._stays(new >> 32, new & 0xFFFFFFFF)
            stays[lost] = found[inverse]
            fresh.append((new, found))
        out[real] = stays
        return out

    def _remember(self, fresh: list) -> None:
        if not fresh:
            return
        keys, first = np.unique(np.concatenate([k for k, _ in fresh]), return_index=True)
        stays = np.concatenate([s for _, s in fresh])[first]
        if len(self.pair_keys) + len(keys) <= CACHE_PAIRS:
            keys, stays = np.concatenate([self.pair_keys, keys]), np.concatenate([self.pair_stays, stays])
            order = np.argsort(keys, kind="stable")
            keys, stays = keys[order], stays[order]
        self.pair_keys, self.pair_stays = keys, stays

    def _arcs(self, codes: np.ndarray, rest: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Start, length and piece of every lexicon arc over the characters; rest: characters from each one to its word's end."""
        starts, sizes, written = [], [], []
        at, state, size = np.arange(len(codes)), np.zeros(len(codes), np.int64), 0
        while len(at):
            found = _find(self.arc_keys, state << 21 | codes[at + size])
            at, state, size = at[found >= 0], self.arc_to[found[found >= 0]], size + 1
            piece = self.final[state]
            ends = piece >= 0
            starts.append(at[ends])
            sizes.append(np.full(int(ends.sum()), size))
            written.append(piece[ends])
            more = rest[at] > size
            at, state = at[more], state[more]
        single = np.zeros(len(codes), bool)
        if starts:
            single[starts[0]] = True
        bare = np.flatnonzero(~single)  # byte fallback
        return np.concatenate([*starts, bare]), np.concatenate([*sizes, np.ones(len(bare), np.int64)]), np.concatenate([*written, np.full(len(bare), -1)])

    def paths(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids on the shortest path of each word (not empty), one after the other, and where each word's begin and end: composition
        with all machines, relaxed by end position."""
        lengths = np.fromiter((len(w) for w in words), np.int64, len(words))
        codes = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), "<u4").astype(np.int64)
        first = np.cumsum(lengths) - lengths
        word = np.repeat(np.arange(len(words)), lengths)
        start, size, piece = self._arcs(codes, (first + lengths)[word] - np.arange(len(codes)))
        reach = start - first[word[start]] + size
        order = np.lexsort((start, reach))
        start, size, piece, reach = start[order], size[order], piece[order], reach[order]
        here = start + word[start]  # a word has a node before each character and one at its end
        there = here + size
        cost = np.full(len(codes) + len(words), np.inf, np.float32)
        cost[first + np.arange(len(words))] = 0
        last, back = np.full(len(cost), -1), np.full(len(cost), -1)
        edges = np.searchsorted(reach, np.arange(1, int(lengths.max(initial=0)) + 2))
        weight = np.where(piece >= 0, self.weight[piece], np.float32(self.unknown))
        fresh: list = []
        for lo, hi in zip(edges[:-1], edges[1:], strict=True):
            arcs = lo + np.flatnonzero(np.isfinite(cost[here[lo:hi]]))
            if self.bpe:
                arcs = arcs[self.follows(last[here[arcs]], piece[arcs], fresh)]
            total = cost[here[arcs]] + weight[arcs]
            best = np.lexsort((start[arcs], total, there[arcs]))
            arcs, total = arcs[best], total[best]
            new = np.ones(len(arcs), bool)
            new[1:] = there[arcs][1:] != there[arcs][:-1]
            arcs = arcs[new]
            cost[there[arcs]], last[there[arcs]], back[there[arcs]] = total[new], piece[arcs], arcs
        self._remember(fresh)
        node, owner, rows = first + lengths + np.arange(len(words)), np.arange(len(words)), []
        while len(node):  # back from the ends, all words together
            arc = back[node]
            if (arc < 0).any():
                raise ValueError("a word has no path")
            rows.append((owner, arc))
            node = here[arc]
            more = node > (first + np.arange(len(words)))[owner]
            node, owner = node[more], owner[more]
        owner, arc = np.concatenate([o for o, _ in rows][::-1]), np.concatenate([x for _, x in rows][::-1])
        order = np.lexsort((start[arc], owner))
        ids, at, cuts = piece[arc[order]], start[arc[order]], np.searchsorted(owner[order], np.arange(len(words) + 1))
        if (ids < 0).any():
            spelled = [[i] if i >= 0 else [self.byte_ids[x] for x in chr(codes[p]).encode()] for i, p in zip(ids.tolist(), at.tolist(), strict=True)]
            ends = np.concatenate([[0], np.cumsum([len(x) for x in spelled])])
            ids, cuts = np.array([i for x in spelled for i in x], np.int64), ends[cuts]
        return ids, cuts

    def cut(self, word: str) -> list[str]:
        """A long word cut between neighbours that no piece holds together."""
        if len(word) <= LONG_WORD:
            return [word]
        inner, start, out = self.inner, 0, []
        for at in range(1, len(word)):
            if word[at - 1 : at + 1] not in inner:
                out.append(word[start:at])
                start = at
        out.append(word[start:])
        return out

    def run(self, n: int) -> list[int]:
        """Ids of n blanks that no word takes: merged in pairs from the left while a run of that length is a piece."""
        parts = [1] * n
        while True:
            at = next((k for k in range(len(parts) - 1) if parts[k] + parts[k + 1] in self.runs), None)
            if at is None:
                return [self.runs[p] for p in parts]
            parts[at : at + 2] = [parts[at] + parts[at + 1]]

    def blanks_and_word(self, n: int, ids: list[int]) -> list[int]:
        """n blanks and the word of these ids, whose first blank is the last of the n: it may join the word."""
        single = self.lexicon[BLANK]
        if ids and ids[0] != single:
            return self.run(n - 1) + ids
        return self.run(n) + ids[1:]


def compile_model(path: str) -> Machines:
    """Reads a byte-pair or unigram SentencePiece model with byte fallback and an identity normaliser."""
    pieces, scores, kinds, bpe, spec = [], [], [], False, {}
    with open(path, "rb") as f:
        for number, value in _fields(f.read()):
            if number == 1:
                piece = dict(_fields(value))
                pieces.append(piece[1].decode())
                scores.append(piece.get(2, 0.0))
                kinds.append(piece.get(3, NORMAL))
            elif number == 2:
                model = dict(_fields(value)).get(3, 1)
                if model not in (1, 2):
                    raise ValueError("only unigram and byte-pair models are compiled")
                bpe = model == 2
            elif number == 3:
                spec = dict(_fields(value))
    if spec.get(2) or not spec.get(3, 1) or not spec.get(5, 1):
        raise ValueError("only the identity normaliser with a leading blank is compiled")
    byte_ids = [0] * 256
    for k, (piece, kind) in enumerate(zip(pieces, kinds, strict=True)):
        if kind == BYTE:
            byte_ids[int(piece[3:5], 16)] = k
    normal = [k for k, kind in enumerate(kinds) if kind in (NORMAL, USER)]
    runs = {len(pieces[k]): k for k in normal if not pieces[k].strip(BLANK)} if bpe else {}
    words = [k for k in normal if not bpe or pieces[k].strip(BLANK) or pieces[k] == BLANK]
    rank, left, right = (np.full(len(pieces), -1) for _ in range(3))
    lexicon = {pieces[k]: k for k in words}
    if bpe:
        _merges(pieces, scores, words, lexicon, rank, left, right)
    joins = {lexicon[p[:k]] << 32 | lexicon[p[k:]]: rank[i] for p, i in lexicon.items() for k in range(1, len(p)) if p[:k] in lexicon and p[k:] in lexicon} if bpe else {}
    states: dict[tuple[int, str], int] = {}
    final = [-1]
    for piece, k in lexicon.items():
        state = 0
        for char in piece:
            if (state, char) not in states:
                states[state, char] = len(final)
                final.append(-1)
            state = states[state, char]
        final[state] = k
    keys = np.array([state << 21 | ord(char) for state, char in states], np.int64)
    order = np.argsort(keys)
    join_keys = np.array(sorted(joins), np.int64)
    real = [scores[k] for k in words] or [0.0]
    weight = np.zeros(len(pieces) + 1, np.float32)
    if not bpe:
        for k in words:
            weight[k] = -(len(pieces[k].encode()) * max(real) - 0.1) if kinds[k] == USER else -scores[k]
    inner = {p[k : k + 2] for p in lexicon for k in range(len(p) - 1)}
    return Machines(
        pieces, lexicon, byte_ids, inner, bpe, "collapse" if spec.get(4, 1) else "keep", runs,
        keys[order], np.array(list(states.values()), np.int64)[order], np.array(final), weight, 0.0 if bpe else 10.0 - min(real),
        rank, left, right, join_keys, np.array([joins[k] for k in join_keys.tolist()], np.int64),
    )


def _merges(pieces, scores, words, lexicon, rank, left, right) -> None:
    """Fills in when merging makes each piece and of which two; pieces that no merging makes leave the lexicon."""
    for r, k in enumerate(sorted((k for k in words if len(pieces[k]) > 1), key=lambda k: -scores[k])):
        rank[k] = r
    dead = []
    for k in sorted(words, key=lambda k: rank[k]):
        if rank[k] < 0:
            continue
        parts = list(pieces[k])
        while len(parts) > 2:
            joins = [(rank[lexicon[x + y]], at) for at, (x, y) in enumerate(zip(parts, parts[1:])) if x + y in lexicon]
            if not joins:
                break
            at = min(joins)[1]
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        if len(parts) == 2 and all(p in lexicon for p in parts):
            left[k], right[k] = lexicon[parts[0]], lexicon[parts[1]]
        else:
            dead.append(k)
    for k in dead:
        del lexicon[pieces[k]]


class Codec:
    """Encoder and decoder of one worker process, with a bounded word cache in two generations."""

    def __init__(self, machines: Machines):
        self.m = machines
        self.splits_lines = not any("\n" in p for p in machines.lexicon)
        self.whole = any(BLANK in p.lstrip(BLANK) for p in machines.lexicon)  # pieces that cross blanks: a line is one word
        self.new: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        plain = [p.replace(BLANK, " ").encode() for p in machines.pieces]
        for byte, k in enumerate(machines.byte_ids):
            plain[k] = bytes([byte])
        self.plain_size = np.array([len(p) for p in plain], np.int64)
        self.plain_at = np.cumsum(self.plain_size) - self.plain_size
        self.plain = np.frombuffer(b"".join(plain), np.uint8)

    def normal(self, text: str | None) -> str:
        """The text that the normaliser leaves, with blanks for U+2581."""
        text = (text or "").replace(BLANK, " ")
        return " ".join(x for x in text.split(" ") if x) if self.m.spaces == "collapse" else text

    def encode(self, text: str | None) -> bytes:
        """Packed 4-byte ids of one text."""
        return self.encode_all([text])[0]

    def encode_all(self, texts: list[str | None]) -> list[bytes]:
        """Packed 4-byte ids of each text; the words of all texts that are not cached are composed together."""
        split = [self._words(t) for t in texts]
        distinct = set().union(*split)
        missing = distinct.difference(self.new)
        if len(self.new) + len(missing) > CACHE_WORDS:
            self.old, self.new, missing = self.new, {}, distinct
        unknown = [w for w in missing if w not in self.old]
        self.new.update((w, self.old[w]) for w in missing if w in self.old)
        self.new.update(zip(unknown, self._compose(unknown), strict=True))
        return [b"".join(map(self.new.__getitem__, words)) for words in split]

    def _words(self, text: str | None) -> list[str]:
        text = self.normal(text)
        if not text:
            return []
        words: list[str] = []
        for k, line in enumerate((" " + text).split("\n") if self.splits_lines else [" " + text]):
            if k:
                words.append("\n")
            if self.whole:
                words.extend([line.replace(" ", BLANK)] if line else [])
            elif "  " in line or line.endswith(" "):
                words.extend(self._with_runs(line))
            else:
                first, *rest = line.split(" ")
                if first:
                    words.append(first)
                words.extend([BLANK + w for w in rest])
        return words

    def _compose(self, words: list[str]) -> list[bytes]:
        """Packed ids of words: long ones in parts, several leading blanks (in byte-pair models) apart from the word."""
        parts: list[str] = []
        special: list[tuple[int, int, int]] = []  # the word's place, blanks apart, parts
        for k, w in enumerate(words):
            apart = 0
            if self.m.bpe and (w == BLANK or w[:2] == BLANK * 2):
                apart = len(w) - len(w.lstrip(BLANK))
                w = BLANK + w[apart:] if apart < len(w) else ""
            if apart or len(w) > LONG_WORD:
                own = self.m.cut(w) if w else []
                special.append((k, apart, len(own)))
                parts += own
            else:
                parts.append(w)
        if not parts:
            parts = [BLANK]
        ids, cuts = self.m.paths(parts)
        raw, ends = ids.astype("<i4").tobytes(), (4 * cuts).tolist()
        out, at = [], 0
        for k, apart, n in [*special, (len(words), 0, 0)]:
            plain = k - len(out)
            out += [raw[a:b] for a, b in zip(ends[at : at + plain], ends[at + 1 : at + plain + 1], strict=True)]
            at += plain
            if k < len(words):
                own = raw[ends[at] : ends[at + n]]
                at += n
                out.append(np.array(self.m.blanks_and_word(apart, np.frombuffer(own, "<i4").tolist()), "<i4").tobytes() if apart else own)
        return out

    def _with_runs(self, line: str):
        first, *rest = line.split(" ")
        if first:
            yield first
        n = 0
        for w in rest:
            n += 1
            if w:
                yield BLANK * n + w
                n = 0
        if n:
            yield BLANK * n

    def decode(self, ids: np.ndarray) -> str:
        """The text of ids: pieces' characters, blanks for U+2581, bytes for byte pieces, without the leading blank."""
        size = self.plain_size[ids]
        ends = np.cumsum(size)
        raw = self.plain[np.repeat(self.plain_at[ids] - ends + size, size) + np.arange(ends[-1] if len(ends) else 0)].tobytes()
        return raw.decode(errors="replace")[1:] if raw[:1] == b" " else raw.decode(errors="replace")


_CODECS: dict[int, Codec] = {}


def codec(machines, key: int) -> Codec:
    if key not in _CODECS:
        _CODECS.clear()
        _CODECS[key] = Codec(machines.value)
    return _CODECS[key]


def encode(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row a document: doc_id, n_ids, ids, ids_crc32 (of little-endian 4-byte ids) and decoded_ok (decoding gave the text back)."""
    small_batches(docs.sparkSession)
    machines = docs.sparkSession.sparkContext.broadcast(compile_model(model_path))  # bounded by the vocabulary
    key = hash(model_path)

    def run(batches):
        c = codec(machines, key)
        for batch in batches:
            texts = batch["rw_text"].to_pylist()
            packed = [raw for a in range(0, len(texts), TOGETHER) for raw in c.encode_all(texts[a : a + TOGETHER])]
            ok = [c.decode(np.frombuffer(raw, "<i4")) == c.normal(text) for raw, text in zip(packed, texts, strict=True)]
            sizes = np.cumsum([0] + [len(r) // 4 for r in packed])
            ids = pa.ListArray.from_arrays(pa.array(sizes, pa.int32()), pa.array(np.frombuffer(b"".join(packed), "<i4")))
            yield pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(np.diff(sizes), pa.int64()), ids, pa.array([zlib.crc32(r) for r in packed], pa.int64()), pa.array(ok, pa.bool_())], ["doc_id", "n_ids", "ids", "ids_crc32", "decoded_ok"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("rw_text")).mapInArrow(lean(run), "doc_id long, n_ids long, ids array<int>, ids_crc32 long, decoded_ok boolean")


def decode(ids: DataFrame, model_path: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """doc_id and text of encoded documents; null ids give an empty text."""
    machines = ids.sparkSession.sparkContext.broadcast(compile_model(model_path))
    key = hash(model_path)

    def run(batches):
        c = codec(machines, key)
        for batch in batches:
            texts = [c.decode(np.array(x or [], np.int64)) for x in batch["rw_ids"].to_pylist()]
            yield pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(texts, pa.string())], ["doc_id", "text"])

    return ids.select(F.col(id_col).cast("long").alias("doc_id"), F.col(ids_col).alias("rw_ids")).mapInArrow(lean(run), "doc_id long, text string")
