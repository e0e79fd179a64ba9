"""Removal of repeated passages by fixed-block anchors (op4).

Every text is cut into words. Non-overlapping blocks of `block` words, counted from the start of each text,
are the references; every rolling window of as many words is a probe. A window of `window` >= 2 * block - 1
words always holds a whole block, so two equal windows in different texts always meet in an anchor. All
windows that hold an anchor are then compared whole, to the left and the right of it, which extends the hit to the maximal exact repeat.

What is exchanged is small: documents fall into groups of some megabytes, a group sends the distinct
hashes it has, packed and sorted into buckets of the hash space, and gets back one bit a hash: does this
hash matter. A hash that a million documents share is sent once by each group, so no bucket is hot. The
text itself is shuffled once, to form the groups; all steps read that one exchange.

A word goes if any window over it does, so neighbouring hits run together into maximal repeats, whatever their length; two windows count as
equal if both of their independent hashes are (64 and 32 bits of all 13 words).

Null and empty texts have no words. A null doc_id counts as larger than any other. Rows that repeat a doc_id
do not remove each other's words (only a smaller id does).
"""

from __future__ import annotations

import hashlib
from itertools import compress

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleweave.llm.common import group_count, text_bytes
from ruleweave.llm.textnum import U, Words, encoded, mix

NO_ID = np.iinfo(np.int64).max
KEY = 5
LONG_KEY = 12


def _pack(h: np.ndarray, width: int) -> np.ndarray:
    """The low `width` bytes of each hash."""
    return np.ascontiguousarray(h.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width])


def _unpack(raw: bytes, width: int) -> np.ndarray:
    out = np.zeros((len(raw) // width, 8), np.uint8)
    out[:, :width] = np.frombuffer(raw, np.uint8).reshape(-1, width)
    return out.view("<u8").ravel()


def _bits(flags: np.ndarray) -> bytes:
    return np.packbits(flags).tobytes()


def _flags(raw: bytes, n: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(raw, np.uint8), count=n).astype(bool)


class _Group:
    """One group of documents: its words, the anchors' hashes and, once the answers are known, the windows to compare."""

    def __init__(self, docs: pa.Table, block: int, buckets: int):
        order = np.argsort(docs["rw_id"].to_numpy(), kind="stable")
        self.docs = docs.take(pa.array(order))
        self.ids = self.docs["rw_id"].to_numpy()
        self.texts = encoded(self.docs["rw_text"].to_pylist())
        self.words = Words(self.texts)
        self.block, self.buckets = block, buckets
        self.hashes = self.words.hashes()
        self.at, h = self.words.windows(self.hashes, block)
        # the bucket comes from the top bits, the key from the low ones; sorted by both, each group lists its hashes alike every time
        self.bucket_of = ((h >> U(40)) * U(buckets) >> U(24)).astype(np.int64)
        self.sorted_keys, self.slot, self.times = np.unique(self.bucket_of.astype(U) << U(40) | h & U((1 << 40) - 1), return_inverse=True, return_counts=True)

    def offers(self, group: int) -> pa.Table:
        words = self.words
        is_block = (self.at - words.first[words.text_of[self.at]]) % self.block == 0
        blocks = np.zeros(len(self.sorted_keys), bool)
        blocks[self.slot[is_block]] = True
        return self._rows(group, self.sorted_keys >> U(40), lambda s: {"rw_keys": _pack(self.sorted_keys[s], KEY).tobytes(), "rw_marks": _bits(blocks[s]) + _bits(self.times[s] > 1)}, ANSWER_IN)

    def _rows(self, group, bucket, payload, schema) -> pa.Table:
        edges = np.flatnonzero(np.diff(bucket.astype(np.int64), prepend=-1, append=-1)) if len(bucket) else np.zeros(1, np.int64)
        rows = [{"rw_group": group, "rw_bucket": int(bucket[a]), **payload(slice(a, b))} for a, b in zip(edges[:-1], edges[1:], strict=True) if b > a]
        return pa.Table.from_pylist(rows, schema)

    def anchored(self, answers: pa.Table) -> np.ndarray:
        """Positions whose block-long window is an anchor."""
        hot = np.zeros(len(self.sorted_keys), bool)
        bucket = (self.sorted_keys >> U(40)).astype(np.int64)
        for b, raw in zip(answers["rw_bucket"].to_pylist(), answers["rw_bits"].to_pylist(), strict=True):
            lo, hi = np.searchsorted(bucket, [b, b + 1])
            hot[lo:hi] = _flags(raw, hi - lo)
        return self.at[hot[self.slot]] if len(self.slot) else self.at

    def windows(self, anchors: np.ndarray, window: int) -> None:
        """The windows that hold an anchor, and their two hashes, each window's sequence once with its smallest id in the group."""
        n, w = len(self.hashes), self.words
        near = np.zeros(n + 1, np.int64)
        np.add.at(near, np.maximum(anchors - (window - self.block), 0), 1)
        np.add.at(near, anchors + 1, -1)
        at, h = w.windows(self.hashes, window)
        keep = np.cumsum(near)[at] > 0
        self.win_at, self.win_h = at[keep], h[keep]
        _, second = w.windows(w.hashes(seed=1), window)
        self.win_h2 = mix(second[keep]) & U(0xFFFFFFFF)
        self.win_bucket = ((self.win_h >> U(40)) * U(self.buckets) >> U(24)).astype(np.int64)
        # text_of rises with the id: the first of equal sequences has the smallest id of the group
        order = np.lexsort((self.win_h2, self.win_h))
        a, b = self.win_h[order], self.win_h2[order]
        new = np.ones(len(order), bool)
        new[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1])
        self.seq = np.empty(len(order), np.int64)
        self.seq[order] = np.cumsum(new) - 1
        self.first_of = order[new]
        # sent by bucket and document: equal ids stand together
        self.sent = np.lexsort((w.text_of[self.win_at[self.first_of]], self.win_bucket[self.first_of]))

    def window_offers(self, group: int) -> pa.Table:
        f = self.first_of[self.sent]
        raw = np.concatenate([_pack(self.win_h[f], 8), _pack(self.win_h2[f], 4)], axis=1)
        ids = self.ids[self.words.text_of[self.win_at[f]]].astype("<i8")
        return self._rows(group, self.win_bucket[f], lambda s: {"rw_keys": raw[s].tobytes(), "rw_marks": ids[s].tobytes()}, ANSWER_IN)

    def removed(self, answers: pa.Table, window: int) -> np.ndarray:
        """One flag a word: covered by a window that also starts in a document with a smaller id."""
        bucket = self.win_bucket[self.first_of[self.sent]]
        earlier = np.zeros(len(self.first_of), bool)
        for b, raw in zip(answers["rw_bucket"].to_pylist(), answers["rw_bits"].to_pylist(), strict=True):
            lo, hi = np.searchsorted(bucket, [b, b + 1])
            earlier[self.sent[lo:hi]] = _flags(raw, hi - lo)
        ids = self.ids[self.words.text_of[self.win_at]]
        gone = earlier[self.seq] | (ids > ids[self.first_of][self.seq]) if len(self.seq) else np.zeros(0, bool)
        cover = np.zeros(len(self.hashes) + 1, np.int64)
        np.add.at(cover, self.win_at[gone], 1)
        np.add.at(cover, self.win_at[gone] + window, -1)
        return np.cumsum(cover)[:-1] > 0


ANSWER_IN = pa.schema([("rw_group", pa.int64()), ("rw_bucket", pa.int64()), ("rw_keys", pa.binary()), ("rw_marks", pa.binary())])
ANSWER_OUT = pa.schema([("rw_group", pa.int64()), ("rw_bucket", pa.int64()), ("rw_step", pa.int64()), ("rw_bits", pa.binary())])


def _split(table: pa.Table, width: int) -> tuple[list[int], list[bytes], list[bytes], np.ndarray]:
    keys, marks = table["rw_keys"].to_pylist(), table["rw_marks"].to_pylist()
    return table["rw_group"].to_pylist(), keys, marks, np.cumsum([0] + [len(k) // width for k in keys])


def _answers(groups, bucket, step, flags, edges) -> pa.Table:
    return pa.Table.from_pydict({"rw_group": groups, "rw_bucket": [bucket] * len(groups), "rw_step": [step] * len(groups), "rw_bits": [_bits(flags[a:b]) for a, b in zip(edges[:-1], edges[1:], strict=True)]}, ANSWER_OUT)


def _meet_anchors(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
    """For each hash of a bucket: is a reference block among its places, and is there more than one place."""
    groups, keys, marks, edges = _split(table, KEY)
    h = _unpack(b"".join(keys), KEY)
    block, many = (np.concatenate([_flags(m[part * (len(m) // 2) :][: len(m) // 2], len(k) // KEY) for k, m in zip(keys, marks, strict=True)] or [np.zeros(0, bool)]) for part in (0, 1))
    _, inverse, places = np.unique(h, return_inverse=True, return_counts=True)
    has_block = np.zeros(len(places), bool)
    has_block[inverse[block]] = True
    several = places > 1
    several[inverse[many]] = True
    return _answers(groups, key[0].as_py(), 1, (has_block & several)[inverse], edges)


def _meet_windows(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
    """For each sequence a group sent: has another group a smaller id with the same sequence."""
    groups, keys, marks, edges = _split(table, LONG_KEY)
    raw = np.frombuffer(b"".join(keys), np.uint8).reshape(-1, LONG_KEY)
    h, h2 = raw[:, :8].copy().view("<u8").ravel(), raw[:, 8:].copy().view("<u4").ravel()
    ids = np.frombuffer(b"".join(marks), "<i8")
    order = np.lexsort((ids, h2, h))
    new = np.ones(len(order), bool)
    new[1:] = (h[order][1:] != h[order][:-1]) | (h2[order][1:] != h2[order][:-1])
    least = ids[order][new][np.cumsum(new) - 1] if len(order) else ids
    earlier = np.zeros(len(order), bool)
    earlier[order] = least < ids[order]
    return _answers(groups, key[0].as_py(), 2, earlier, edges)


def repeats(docs: DataFrame, window: int = 13, block: int = 7, id_col: str = "doc_id", text_col: str = "text", digest: bool = False) -> DataFrame:
    """One row a document: id, n_words, n_removed, spans (maximal removed runs as [first word, end) pairs) and kept_text.

    With digest, kept_sha256 (of the kept words joined by a space) stands instead of spans and kept_text.
    """
    if window < 2 * block - 1:
        raise ValueError("a window must be at least 2 * block - 1 words long to hold a whole block")
    total = text_bytes(docs, text_col)
    n_groups = group_count(total)
    n_buckets = n_groups
    grouped = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)).alias("rw_id"), F.col(id_col).isNull().alias("rw_no_id"), F.col(text_col).alias("rw_text"))
    # rows that share a doc_id, or have none, are spread like others: what counts between them is the order of ids alone
    grouped = grouped.withColumn("rw_group", F.pmod(F.xxhash64("rw_id", "rw_text"), F.lit(n_groups)))
    in_schema, out_schema = "rw_group long, rw_bucket long, rw_keys binary, rw_marks binary", "rw_group long, rw_bucket long, rw_step long, rw_bits binary"

    def offer(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        return _Group(table, block, n_buckets).offers(key[0].as_py())

    def offer_windows(key: tuple[pa.Scalar, ...], table: pa.Table, answers: pa.Table) -> pa.Table:
        if not table.num_rows:
            return ANSWER_IN.empty_table()
        g = _Group(table, block, n_buckets)
        g.windows(g.anchored(answers), window)
        return g.window_offers(key[0].as_py())

    def finish(key: tuple[pa.Scalar, ...], table: pa.Table, answers: pa.Table) -> pa.Table:
        if not table.num_rows:
            return result.empty_table()
        steps = answers["rw_step"].to_numpy()
        first, second = answers.filter(pa.array(steps == 1)), answers.filter(pa.array(steps == 2))
        g = _Group(table, block, n_buckets)
        g.windows(g.anchored(first), window)
        gone = g.removed(second, window)
        rows = {"doc_id": [None if no else int(i) for i, no in zip(g.ids, g.docs["rw_no_id"].to_pylist(), strict=True)], "n_words": g.words.counts, "n_removed": np.zeros(len(g.ids), np.int64)}
        kept, spans = [], []
        for k, text in enumerate(g.texts):
            flags = gone[g.words.first[k] : g.words.first[k + 1]]
            rows["n_removed"][k] = flags.sum()
            words = text.split()
            kept.append(b" ".join(compress(words, (~flags).tolist()) if rows["n_removed"][k] else words))
            if not digest:
                spans.append(np.flatnonzero(np.diff(flags.astype(np.int8), prepend=0, append=0)).reshape(-1, 2).tolist())
        if digest:
            rows["kept_sha256"] = [hashlib.sha256(k).hexdigest() for k in kept]
        else:
            rows |= {"spans": spans, "kept_text": [k.decode() for k in kept]}
        return pa.Table.from_pydict(rows, result)

    fields = [("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64())]
    result = pa.schema(fields + ([("kept_sha256", pa.string())] if digest else [("spans", pa.list_(pa.list_(pa.int64()))), ("kept_text", pa.string())]))
    out = "doc_id long, n_words long, n_removed long, " + ("kept_sha256 string" if digest else "spans array<array<long>>, kept_text string")
    anchors = grouped.groupBy("rw_group").applyInArrow(offer, in_schema).groupBy("rw_bucket").applyInArrow(_meet_anchors, out_schema)
    met = grouped.groupBy("rw_group").cogroup(anchors.groupBy("rw_group")).applyInArrow(offer_windows, in_schema).groupBy("rw_bucket").applyInArrow(_meet_windows, out_schema)
    return grouped.groupBy("rw_group").cogroup(anchors.unionByName(met).groupBy("rw_group")).applyInArrow(finish, out)
