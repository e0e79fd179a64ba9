"""Token-id files (op1): frequency-ranked ids in byte-aligned variable-length coding with separate control bytes.

An id is replaced by its rank (0 = the most frequent id of the corpus), a rank is stored in 1 to 4 bytes, and
the byte counts stand apart, two bits each, four ranks to a control byte. A reader looks up each control
byte in a table of 256 rows and gathers all ranks of a block with numpy.

The format: folder/ranks (Parquet: rank, id) and folder/blocks (Parquet; a row is a block of whole documents
in ascending doc_id order: shard, block, shard_start, doc_ids, sizes, control, data). Parquet is the
container, so the files can be in any store that Spark writes to, and a lost task is just written again.

Null texts count as empty, null doc_ids come first, documents with equal doc_ids follow each other in the
order of their ids. An empty table makes a file without blocks.
"""

from __future__ import annotations

import json
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ruleweave.llm.common import shared_dir, shuffle_width, staged
from ruleweave.llm.textnum import Words, encoded

BLOCK_TOKENS = 1 << 16
CACHE_WORDS, JOINED, CHUNK_BYTES = 1_500_000, 256, 2 << 20
SHARD_BYTES = 128 << 20
# How the public word-level file normalises and splits.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
NORMALIZER = {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": "\\s+"}, "content": " "}, {"type": "Lowercase"}]}
_SIGN_KINDS = np.full(256, 3, np.uint8)  # letters 1, digits 2, other signs 3, uncertain 4
_SIGN_KINDS[[*range(65, 91), *range(97, 123)]] = 1
_SIGN_KINDS[48:58] = 2
_SIGN_KINDS[[0x27, 0x3C, *range(0x00, 0x20), *range(0x7F, 0x100)]] = 4
_LATIN_TAIL = np.zeros(256, bool)
_LATIN_TAIL[0x80:0xC0] = True
_LATIN_TAIL[[0x97, 0xB7]] = False
_LENGTHS = (np.arange(256)[:, None] >> np.array([0, 2, 4, 6]) & 3) + 1


class WordEncoder:
    """Ids of texts by a tokenizers file whose tokens never cross ASCII blanks: a word is encoded when it is not in the cache.

    The cache is a few arrays: words by two 64-bit hashes, and their ids end to end. It holds at most CACHE_WORDS words; beyond that,
    those not used lately go. New words are encoded many in one text. If the file splits words like SPLIT after lower-casing and marks
    each part's last token (end_of_word_suffix), the marks tell which ids are whose, since the number of parts of words of plain
    letters, digits and signs is counted here; other words are encoded one by one.
    """

    def __init__(self, path: str, dtype: str = "<u4"):
        from tokenizers import Tokenizer

        self.tokenizer, self.dtype = Tokenizer.from_file(path), np.dtype(dtype)
        with open(path, encoding="utf-8") as f:
            model = json.load(f)
        suffix = model["model"].get("end_of_word_suffix")
        splits = [x.get("pattern", {}).get("Regex") for x in (model["pre_tokenizer"] or {}).get("pretokenizers", [])]
        self.marked = bool(suffix) and model["normalizer"] == NORMALIZER and SPLIT in splits
        self.is_end = np.zeros(self.tokenizer.get_vocab_size(), bool)
        if self.marked:
            self.is_end[[i for token, i in self.tokenizer.get_vocab().items() if token.endswith(suffix)]] = True
        self.keys, self.keys2 = np.empty(0, np.uint64), np.empty(0, np.uint64)
        self.start, self.size, self.used = np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.int64)
        self.ids, self.clock = np.empty(0, self.dtype), 0

    def encode(self, texts: list[bytes]) -> list[bytes]:
        out, at = [], 0
        while at < len(texts):
            end, size = at, 0
            while end < len(texts) and (end == at or size + len(texts[end]) <= CHUNK_BYTES):
                size += len(texts[end])
                end += 1
            out += self._chunk(texts[at:end])
            at = end
        return out

    def _chunk(self, texts: list[bytes]) -> list[bytes]:
        words = Words(texts)
        h, h2 = words.hashes(), words.hashes(seed=1)
        distinct, first, inverse = np.unique(h, return_index=True, return_inverse=True)
        if not (h2[first][inverse] == h2).all():  # two words with one hash: too rare to be fast
            return [b"".join(self._singly(t.split())) for t in texts]
        second = h2[first]
        at = np.searchsorted(self.keys, distinct)
        known = at < len(self.keys)
        known[known] = (self.keys[at[known]] == distinct[known]) & (self.keys2[at[known]] == second[known])
        self.clock += 1
        self.used[at[known]] = self.clock
        if not known.all():
            new = np.flatnonzero(~known)
            raw = words.buf.tobytes()
            fresh = [raw[a:b] for a, b in zip(words.starts[first[new]].tolist(), words.ends[first[new]].tolist(), strict=True)]
            self._insert(distinct[new], second[new], self._together(fresh))
            at = np.searchsorted(self.keys, distinct)
        start, size = self.start[at][inverse], self.size[at][inverse]
        ends = np.concatenate([[0], np.cumsum(size)])
        flat = self.ids[np.repeat(start - ends[:-1], size) + np.arange(ends[-1])].tobytes()
        cuts = (ends[words.first] * self.dtype.itemsize).tolist()
        return [flat[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)]

    def _insert(self, keys: np.ndarray, keys2: np.ndarray, encoded_words: list[np.ndarray]) -> None:
        if len(self.keys) and len(self.keys) + len(keys) > CACHE_WORDS:
            kept = np.flatnonzero(self.used >= np.sort(self.used)[-min(len(self.used), max(1, CACHE_WORDS // 2))])
            if len(kept) + len(keys) > CACHE_WORDS:  # only what the present texts need
                kept = np.flatnonzero(self.used == self.clock)
            ends = np.cumsum(self.size[kept])
            self.ids = self.ids[np.repeat(self.start[kept] - ends + self.size[kept], self.size[kept]) + np.arange(ends[-1] if len(ends) else 0)]
            self.keys, self.keys2, self.used, self.size = self.keys[kept], self.keys2[kept], self.used[kept], self.size[kept]
            self.start = ends - self.size
        sizes = np.array([len(x) for x in encoded_words], np.int64)
        starts = len(self.ids) + np.cumsum(sizes) - sizes
        self.ids = np.concatenate([self.ids, *encoded_words])
        # a key of equal first hash gives way to the new word
        at = np.searchsorted(self.keys, keys)
        same = at < len(self.keys)
        same[same] = self.keys[at[same]] == keys[same]
        stay = np.ones(len(self.keys), bool)
        stay[at[same]] = False
        merged = np.concatenate([self.keys[stay], keys])
        order = np.argsort(merged, kind="stable")
        self.keys = merged[order]
        self.keys2 = np.concatenate([self.keys2[stay], keys2])[order]
        self.start = np.concatenate([self.start[stay], starts])[order]
        self.size = np.concatenate([self.size[stay], sizes])[order]
        self.used = np.concatenate([self.used[stay], np.full(len(keys), self.clock)])[order]

    def _singly(self, words: list[bytes]) -> list[bytes]:
        return [np.array(e.ids, self.dtype).tobytes() for e in self.tokenizer.encode_batch_fast([w.decode() for w in words], add_special_tokens=False)]

    def _together(self, words: list[bytes]) -> list[np.ndarray]:
        """Ids of each word."""
        out: list[np.ndarray] = [None] * len(words)
        parts, plain = self._parts(words) if self.marked else (np.zeros(len(words), np.int64), np.zeros(len(words), bool))
        easy, hard = np.flatnonzero(plain), np.flatnonzero(~plain).tolist()
        groups = [easy[k : k + JOINED] for k in range(0, len(easy), JOINED)]
        texts = [" ".join([words[k].decode() for k in g.tolist()]) for g in groups]
        for g, e in zip(groups, self.tokenizer.encode_batch_fast(texts, add_special_tokens=False), strict=True):
            ids = np.array(e.ids, self.dtype)
            ends = np.flatnonzero(self.is_end[ids]) + 1
            last = np.cumsum(parts[g])
            if len(ends) != last[-1] or ends[-1] != len(ids):
                hard += g.tolist()
                continue
            cuts = ends[last - 1]
            for k, a, b in zip(g.tolist(), np.concatenate([[0], cuts[:-1]]).tolist(), cuts.tolist(), strict=True):
                out[k] = ids[a:b]
        for k, raw in zip(hard, self._singly([words[k] for k in hard]), strict=True):
            out[k] = np.frombuffer(raw, self.dtype)
        return out

    @staticmethod
    def _parts(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """How many parts SPLIT makes of each word, and whether that is certain: ASCII without quotes and '<', and the letters of Latin-1."""
        sizes = np.array([len(w) for w in words], np.int64)
        buf = np.frombuffer(b"".join(words) + b"\0", np.uint8)
        kind = _SIGN_KINDS[buf]
        lead = np.flatnonzero(buf[:-1] == 0xC3)
        letter = lead[_LATIN_TAIL[buf[lead + 1]]]
        kind[letter] = kind[letter + 1] = 1
        first = np.cumsum(sizes) - sizes
        turn = np.ones(len(buf), bool)
        turn[1:] = (kind[1:] != kind[:-1]) | (kind[1:] == 2)
        turn[first] = True
        return np.add.reduceat(turn[:-1].astype(np.int64), first), np.maximum.reduceat(kind[:-1], first) < 4


_ENCODERS: dict[tuple[str, str], WordEncoder] = {}


def word_encoder(path: str, dtype: str) -> WordEncoder:
    """The encoder of this worker process; its cache lives as long as the process."""
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    if (path, dtype) not in _ENCODERS:
        _ENCODERS[path, dtype] = WordEncoder(path, dtype)
    return _ENCODERS[path, dtype]


def encode(docs: DataFrame, tokenizer_path: str, end_id: int | None = 1, vocabulary: int = 1 << 16, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and ids (packed little-endian, 2 bytes an id if the vocabulary allows, else 4), with end_id after each document."""
    dtype = "<u2" if vocabulary <= 1 << 16 else "<u4"
    end = b"" if end_id is None else np.array([end_id], dtype).tobytes()

    def run(batches):
        encoder = word_encoder(tokenizer_path, dtype)
        for batch in batches:
            ids = [x + end for x in encoder.encode(encoded(batch["rw_text"].to_pylist()))]
            yield pa.RecordBatch.from_arrays([batch["doc_id"].cast(pa.int64()), pa.array(ids, pa.binary())], ["doc_id", "ids"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("rw_text")).mapInArrow(run, "doc_id long, ids binary")


def id_counts(ids: DataFrame, dtype: str) -> DataFrame:
    """id, n over all documents: each task counts its own, then the counts meet."""

    def run(batches):
        total = np.zeros(0, np.int64)
        for batch in batches:
            n = np.bincount(np.frombuffer(b"".join(batch["ids"].to_pylist()), dtype))
            if len(n) > len(total):
                n[: len(total)] += total
                total = n
            else:
                total[: len(n)] += n
        seen = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(seen, pa.int64()), pa.array(total[seen], pa.int64())], ["id", "n"])

    return ids.select("ids").mapInArrow(run, "id long, n long").groupBy("id").agg(F.sum("n").alias("n"))


def pack(ranks: np.ndarray) -> tuple[bytes, bytes]:
    """Control bytes and data bytes of one block of ranks."""
    ranks = ranks.astype("<u4")
    size = 1 + (ranks > 0xFF) + (ranks > 0xFFFF) + (ranks > 0xFFFFFF)
    code = np.zeros(-(-len(ranks) // 4) * 4, np.uint8)
    code[: len(ranks)] = size - 1
    control = (code.reshape(-1, 4) << np.array([0, 2, 4, 6], np.uint8)).sum(axis=1).astype(np.uint8)
    data = ranks.view(np.uint8).reshape(-1, 4)[np.arange(4) < size[:, None]]
    return control.tobytes(), data.tobytes()


def unpack(control: bytes, data: bytes, n: int) -> np.ndarray:
    """The n ranks of a block: lengths by table lookup, then one gather for each byte position."""
    size = _LENGTHS[np.frombuffer(control, np.uint8)].ravel()[:n]
    at = np.cumsum(size) - size
    raw = np.frombuffer(data + b"\0\0\0", np.uint8).astype(np.uint32)
    out = raw[at] if n else np.zeros(0, np.uint32)
    for k in (1, 2, 3):
        more = size > k
        if not more.any():
            break
        out[more] |= raw[at[more] + k] << np.uint32(8 * k)
    return out


def write(ids: DataFrame, folder: str, dtype: str = "<u2", shards: int | None = None) -> str:
    """Writes encoded documents (see encode; stage them first, they are read three times) as a token file."""
    spark = ids.sparkSession
    counts = id_counts(ids, dtype).orderBy(F.desc("n"), "id").collect()  # one row an id of the vocabulary at most
    order = np.array([r.id for r in counts], np.int64)
    rank_of = np.zeros(order.max(initial=0) + 1, np.uint32)
    rank_of[order] = np.arange(len(order))
    spark.createDataFrame([(k, int(i)) for k, i in enumerate(order)], "rank long, id long").coalesce(1).write.parquet(f"{folder}/ranks")
    ranks = spark.sparkContext.broadcast(rank_of)
    if shards is None:
        total = ids.agg(F.sum(F.octet_length("ids"))).first()[0] or 0
        shards = max(shuffle_width(spark), -(-total // SHARD_BYTES))

    def run(batches):
        shard, block, start = TaskContext.get().partitionId(), 0, 0
        held_ids, held, size = [], [], 0

        def flush():
            nonlocal block, start, held_ids, held, size
            sizes = np.array([len(x) for x in held], np.int64) // np.dtype(dtype).itemsize
            control, data = pack(ranks.value[np.frombuffer(b"".join(held), dtype)])
            row = {"shard": shard, "block": block, "shard_start": start, "doc_ids": held_ids, "sizes": sizes.astype("<u4").tobytes(), "control": control, "data": data}
            block, start, held_ids, held, size = block + 1, start + int(sizes.sum()), [], [], 0
            return pa.RecordBatch.from_pylist([row], BLOCKS)

        for batch in batches:
            for doc_id, x in zip(batch["doc_id"].to_pylist(), batch["ids"].to_pylist(), strict=True):
                held_ids.append(doc_id)
                held.append(x)
                size += len(x) // np.dtype(dtype).itemsize
                if size >= BLOCK_TOKENS:
                    yield flush()
        if held:
            yield flush()

    ordered = ids.repartitionByRange(shards, "doc_id").sortWithinPartitions("doc_id", "ids")
    ordered.mapInArrow(run, "shard long, block long, shard_start long, doc_ids array<long>, sizes binary, control binary, data binary").write.option("compression", "none").parquet(f"{folder}/blocks")
    return folder


BLOCKS = pa.schema([("shard", pa.int64()), ("block", pa.int64()), ("shard_start", pa.int64()), ("doc_ids", pa.list_(pa.int64())), ("sizes", pa.binary()), ("control", pa.binary()), ("data", pa.binary())])


def read(spark: SparkSession, folder: str, with_ids: bool = True) -> DataFrame:
    """Documents of a token file: doc_id, start (ids before it), n_tokens, ids_crc32 and, if asked for, ids as array<int>."""
    blocks = spark.read.parquet(f"{folder}/blocks")
    shard_sizes = blocks.groupBy("shard").agg(F.max_by(F.struct("shard_start", "sizes"), "block").alias("last")).orderBy("shard").collect()  # a row a shard
    offsets, total = {}, 0
    for r in shard_sizes:
        offsets[r.shard] = total
        total += r.last.shard_start + int(np.frombuffer(r.last.sizes, "<u4").sum(dtype=np.int64))
    ids = np.array([r.id for r in spark.read.parquet(f"{folder}/ranks").orderBy("rank").collect()], "<u4")
    id_of = spark.sparkContext.broadcast(ids)

    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                sizes = np.frombuffer(row["sizes"], "<u4").astype(np.int64)
                flat = id_of.value[unpack(row["control"], row["data"], int(sizes.sum()))]
                ends = np.cumsum(sizes)
                parts = [flat[e - s : e] for s, e in zip(sizes, ends, strict=True)]
                columns = [pa.array(row["doc_ids"], pa.int64()), pa.array(offsets[row["shard"]] + row["shard_start"] + ends - sizes), pa.array(sizes), pa.array([zlib.crc32(p.tobytes()) for p in parts], pa.int64())]
                if with_ids:
                    columns.append(pa.array([p.astype(np.int32) for p in parts], pa.list_(pa.int32())))
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "start", "n_tokens", "ids_crc32", "ids"][: len(columns)])

    return blocks.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long" + (", ids array<int>" if with_ids else ""))


def encode_write_read(docs: DataFrame, tokenizer_path: str, end_id: int = 1, vocabulary: int = 1 << 16, with_ids: bool = False) -> DataFrame:
    """The whole way: encode once into a staged table, write the token file from it, read it back."""
    spark = docs.sparkSession
    ids = staged(encode(docs, tokenizer_path, end_id, vocabulary))
    return read(spark, write(ids, shared_dir(spark), "<u2" if vocabulary <= 1 << 16 else "<u4"), with_ids)
