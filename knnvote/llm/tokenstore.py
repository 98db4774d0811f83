"""A content-addressed store of token ids: chunks cut by a rolling hash, document recipes, Merkle manifests.

Folder layout, all Parquet:

- ``chunks``: (hash, n, payload) - every distinct chunk once; payload is the zstandard-compressed ids,
  little-endian, two bytes each where the vocabulary fits them and four otherwise.
- ``recipes``: (doc_id, start, n_tokens, root, hashes, part), files and rows in ascending doc_id order; hashes are
  the 16-byte addresses of the document's chunks, root is the Merkle root over them, start the number of ids
  in all documents before, part a range of documents.
- ``manifest``: (part, start, docs, ids, root): one Merkle root over the recipes of every part.
- ``head``: (parts, docs, ids, root): one row, whose root is over those of the parts and names the store.
"""

from __future__ import annotations

import hashlib
import os
import re
import sys
import zlib
from array import array
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import blocks_of, settle, small_batches

VOCABULARY = "word_bpe_49k.json"
END = 2
MIN_CHUNK, MEAN_BITS, MAX_CHUNK = 128, 10, 4096  # ids; a cut comes every 2**MEAN_BITS ids or so
ADDRESS = 16  # bytes of blake2b that name a chunk
WORDS_KEPT = 600_000  # encodings of words a worker remembers
BLOCK = 1 << 21  # characters encoded at a time
SEEN = 1_000_000  # chunk addresses a task remembers, to send a chunk once


# ---- encoding -----------------------------------------------------------------------------

def _byte_letters() -> dict[int, str]:
    """Latin letters beyond ASCII as the visible characters that byte-level vocabularies write for their UTF-8 bytes."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in plain]
    sign = {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(hidden)}
    return {c: "".join(sign[b] for b in chr(c).encode()) for c in range(128, 256)}


#: How the vocabulary splits lower-cased text, here for Latin-1 letters.
_PIECE = re.compile("'s|'t|'re|'ve|'m|'ll|'d|[a-zß-öø-ÿ]+|[0-9]|[^\\sa-zß-öø-ÿ0-9]+")
#: Bytes of Latin-1 text that _PIECE is known to split as the vocabulary does.
_PLAIN = bytes([*range(9, 14), *range(32, 127), *range(192, 256)])


class _Words(dict):
    """Encodings of words without white space; WORDS_KEPT of them are remembered, those not asked for lately go first.

    Words of letters alone are cut by the model itself. A word of letters and one more sign is put together from the two each
    time, so that it takes no place.
    """

    def __init__(self, tokenizer, width: str):
        super().__init__()
        self.model, self.tokenizer, self.width, self.signs = tokenizer.model, tokenizer, width, _byte_letters()
        self.kind, self.older = "H" if width == "<u2" else "I", {}

    def __missing__(self, word: str) -> bytes:
        if word[:-1].isalpha() and not word[-1].isalpha():  # of the letters in _PLAIN, isalpha knows just those of _PIECE
            return self[word[:-1]] + self[word[-1]]
        raw = self.older.get(word)
        if raw is None:
            raw = self._encoded(word)
        if len(word) <= 64:
            if len(self) >= WORDS_KEPT // 2:
                self.older = dict(self)
                self.clear()
            self[word] = raw
        return raw

    def _encoded(self, word: str) -> bytes:
        if word.isalpha():
            ids = array(self.kind, [t.id for t in self.model.tokenize(word if word.isascii() else word.translate(self.signs))])
            if sys.byteorder == "big":
                ids.byteswap()
            return ids.tobytes()
        pieces = _PIECE.findall(word)
        if len(pieces) > 1:
            return b"".join([self[p] for p in pieces])
        return np.array(self.tokenizer.encode(word, add_special_tokens=False).ids, self.width).tobytes()


class Encoder:
    """Ids of whole texts by the tokenizers library.

    The vocabulary lower-cases text and never joins pieces across white space, so Latin-1 texts are
    encoded word by word and a word's encoding is remembered; all others are encoded as they stand.
    """

    def __init__(self, vocabulary: str = VOCABULARY):
        import public_tokenizers
        from tokenizers import Tokenizer

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # Spark's tasks are the parallelism
        self.by_word = os.path.basename(vocabulary) == VOCABULARY
        self.tokenizer = Tokenizer.from_file(vocabulary if "/" in vocabulary else public_tokenizers.path(vocabulary))
        self.width = "<u2" if self.tokenizer.get_vocab_size() <= 1 << 16 else "<u4"
        self.words = _Words(self.tokenizer, self.width)

    def _plain(self, text: str) -> bool:
        try:
            return self.by_word and not text.encode("latin-1").translate(None, _PLAIN) and "<|" not in text
        except UnicodeEncodeError:
            return False

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        out = []
        for held in blocks_of(texts, len, BLOCK):
            plain = [self._plain(t) for t in held]
            known = iter(self._by_words([t.lower() for t, p in zip(held, plain, strict=True) if p]))
            out += [next(known) if p else np.array(self.tokenizer.encode(t, add_special_tokens=False).ids, self.width) for t, p in zip(held, plain, strict=True)]
        return out

    def _by_words(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of lower-cased plain texts; each distinct word of them is looked up once."""
        lists = pc.ascii_split_whitespace(pa.array(texts, pa.large_string()))
        words = lists.flatten().dictionary_encode()  # white space at either end leaves an empty word, which has no ids
        # one string cut at blanks is far faster than a value at a time
        one = pa.ListArray.from_arrays(pa.array([0, len(words.dictionary)], pa.int32()), words.dictionary)
        distinct = pc.binary_join(one, pa.scalar(" ", pa.large_string()))[0].as_py().split(" ") if len(words) else []
        raw = [self.words[w] if w else b"" for w in distinct]
        ids, sizes = np.frombuffer(b"".join(raw), self.width), np.array([len(r) for r in raw], np.int32) // np.dtype(self.width).itemsize
        at = words.indices.to_numpy()
        n = sizes[at]
        kind = np.int32 if int(n.sum(dtype=np.int64)) < 2**31 else np.int64
        ends = np.concatenate([np.zeros(1, kind), np.cumsum(n, dtype=kind)])
        first = np.cumsum(sizes, dtype=kind) - sizes
        flat = ids[np.repeat(first[at] - ends[:-1], n) + np.arange(ends[-1], dtype=kind)]
        return np.split(flat, ends[np.cumsum(pc.list_value_length(lists).to_numpy())[:-1]]) if texts else []


@cache
def _encoder(vocabulary: str) -> Encoder:
    return Encoder(vocabulary)


# ---- chunks and hashes --------------------------------------------------------------------

_GEAR = np.random.default_rng(20).integers(0, 2**64, 1 << 16, dtype=np.uint64)


def cuts(ids: np.ndarray) -> list[int]:
    """Ends of the chunks of an id stream: where a hash of the last 16 ids has MEAN_BITS leading zeros, within the size limits."""
    n = len(ids)
    if n <= MIN_CHUNK:
        return [n] if n else []
    h = _GEAR[ids & 0xFFFF]
    for j in (1, 2, 4, 8):
        h[j:] = h[j:] + (h[:-j] << np.uint64(j))
    ends, last = [], 0
    for e in (np.flatnonzero(h >> np.uint64(64 - MEAN_BITS) == 0) + 1).tolist():
        while e - last > MAX_CHUNK:
            last += MAX_CHUNK
            ends.append(last)
        if e - last >= MIN_CHUNK:
            last = e
            ends.append(e)
    while n - last > MAX_CHUNK:
        last += MAX_CHUNK
        ends.append(last)
    if last < n:
        ends.append(n)
    return ends


def address(raw: bytes) -> bytes:
    return hashlib.blake2b(raw, digest_size=ADDRESS).digest()


def merkle(leaves: list[bytes]) -> bytes:
    """Root of a binary hash tree; an odd node moves up as it is. No leaves: the address of nothing."""
    level = leaves or [address(b"")]
    while len(level) > 1:
        level = [address(b"\1" + level[i] + level[i + 1]) if i + 1 < len(level) else level[i] for i in range(0, len(level), 2)]
    return level[0]


_POLY = 0xEDB88320  # of crc32, bits reversed


def _times(a: int, b: int) -> int:
    """Product of two polynomials modulo that of crc32, bit 31 first."""
    p, m = 0, 1 << 31
    while a:
        if a & m:
            p ^= b
            a ^= m
        m >>= 1
        b = (b >> 1) ^ _POLY if b & 1 else b >> 1
    return p


@cache
def _shift(n_bytes: int) -> int:
    """x to the power 8 n_bytes, modulo the polynomial."""
    p, square, n = 1 << 31, 1 << 30, 8 * n_bytes
    while n:
        if n & 1:
            p = _times(square, p)
        square, n = _times(square, square), n >> 1
    return p


def crc_joined(parts: list[tuple[int, int]]) -> int:
    """crc32 of byte strings in a row, from the (crc32, length) of each."""
    crc = 0
    for c, n in parts:
        crc = _times(_shift(n), crc) ^ c
    return crc


# ---- writing ------------------------------------------------------------------------------

_INTAKE = "kind string, key long, doc_id long, n_tokens long, hashes binary, hash binary, n int, payload binary"


def _cut_up(vocabulary: str, end: int):
    names = [c.split()[0] for c in _INTAKE.split(", ")]
    types = {"string": pa.string(), "long": pa.int64(), "int": pa.int32(), "binary": pa.binary()}
    schema = pa.schema([(c.split()[0], types[c.split()[1]]) for c in _INTAKE.split(", ")])

    def run(batches):
        enc, seen, pack = _encoder(vocabulary), set(), zstandard.ZstdCompressor(level=1)
        rows, held = {c: [] for c in names}, 0
        salt = TaskContext.get().partitionId() << 32

        def put(*values):
            for c, v in zip(names, values, strict=True):
                rows[c].append(v)

        for b in batches:
            for doc, ids in zip(b.column(0).to_pylist(), enc.encode([t or "" for t in b.column(1).to_pylist()]), strict=True):
                ids = np.append(ids, np.array([end], ids.dtype))
                names_of, last = [], 0
                for e in cuts(ids):
                    raw = ids[last:e].tobytes()
                    h = address(raw)
                    names_of.append(h)
                    if h not in seen:
                        if len(seen) >= SEEN:
                            seen.clear()
                        seen.add(h)
                        payload = pack.compress(raw)
                        held += len(payload)
                        put("chunk", int.from_bytes(h[:8], "big", signed=True), None, None, None, h, e - last, payload)
                    last = e
                salt += 1
                put("recipe", salt * 0x9E3779B97F4A7C15 % 2**64 - 2**63, doc, len(ids), b"".join(names_of), None, None, None)
                if held > 8_000_000 or len(rows["key"]) > 20_000:
                    yield pa.record_batch([pa.array(rows[c], schema.field(c).type) for c in names], schema=schema)
                    rows, held = {c: [] for c in names}, 0
        if rows["key"]:
            yield pa.record_batch([pa.array(rows[c], schema.field(c).type) for c in names], schema=schema)
        pa.default_memory_pool().release_unused()  # what the pool would hold while the worker waits for other jobs

    return run


def _once(batches):
    """Drops chunks that came before; all copies of a chunk have one key, and rows come in the order of keys."""
    _encoder.cache_clear()  # all texts are encoded by now, and a worker outlives its tasks
    pa.default_memory_pool().release_unused()
    last, seen = None, set()
    for b in batches:
        key, h = b.column(b.schema.get_field_index("key")).to_numpy(), b.column(b.schema.get_field_index("hash"))
        alike = key[1:] == key[:-1]
        again = pc.fill_null(pc.equal(h.slice(1), h.slice(0, max(0, len(h) - 1))), False).to_numpy(zero_copy_only=False)
        if (alike & ~again).any() or not len(key) or key[0] == last:  # two hashes of one key, or a key that goes on
            keep = []
            for k, x in zip(key.tolist(), h.to_pylist(), strict=True):
                if k != last:
                    last, seen = k, set()
                keep.append(x is None or x not in seen)
                seen.add(x)
        else:
            keep = np.concatenate([[True], ~alike])
            last, seen = key[-1], {h[-1].as_py()}
        yield b.filter(pa.array(keep, pa.bool_()))


def _roots(batches):
    for b in batches:
        roots = [merkle(_split(h)) for h in b.column(b.schema.get_field_index("hashes")).to_pylist()]
        yield b.append_column("root", pa.array(roots, pa.binary()))


def _split(hashes: bytes) -> list[bytes]:
    return [hashes[i : i + ADDRESS] for i in range(0, len(hashes), ADDRESS)]


def write_store(docs: DataFrame, path: str, doc_id: str = "doc_id", text: str = "text", vocabulary: str = VOCABULARY, end: int = END) -> None:
    """Encode every whole text, with the end id appended, into a store at `path`.

    Null texts count as empty: their document is the end id alone. Documents with a null id come
    first. Repeated ids keep a recipe each, in the order of their roots. An empty table makes an empty store.
    """
    spark = docs.sparkSession
    small_batches(spark)
    cut = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("t")).mapInArrow(_cut_up(vocabulary, end), _INTAKE)
    once = cut.repartition("key").sortWithinPartitions("key").mapInArrow(_once, _INTAKE)
    once.drop("key").write.option("compression", "zstd").partitionBy("kind").parquet(f"{path}/intake")
    intake = spark.read.schema("doc_id long, n_tokens long, hashes binary, hash binary, n int, payload binary, kind string").parquet(f"{path}/intake")
    recipes = intake.where("kind = 'recipe'").select("doc_id", "n_tokens", "hashes").mapInArrow(_roots, "doc_id long, n_tokens long, hashes binary, root binary")
    ranged = settle(recipes.repartitionByRange("doc_id", "root").withColumn("part", F.spark_partition_id()), "recipes")
    # one row a part
    sums = ranged.groupBy("part").agg(F.sum("n_tokens").alias("ids"))
    before = sums.select("part", (F.sum("ids").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1))).alias("base"))
    inside = W.partitionBy("part").orderBy("doc_id", "root")
    started = ranged.join(F.broadcast(before), "part").withColumn("start", F.coalesce("base", F.lit(0)) + F.coalesce(F.sum("n_tokens").over(inside.rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    started = started.select("doc_id", "start", "n_tokens", "root", "hashes", "part")
    started.repartitionByRange("start").sortWithinPartitions("start").write.parquet(f"{path}/recipes")
    manifest = _sealed(_recipes(spark, path))
    manifest.coalesce(1).write.parquet(f"{path}/manifest")
    _head(_manifest(spark, path)).coalesce(1).write.parquet(f"{path}/head")


_PART = "part int, start long, docs long, ids long, root binary"
_HEAD = "parts long, docs long, ids long, root binary"


def _sealed(recipes: DataFrame) -> DataFrame:
    """The manifest that recipes give: a row a part, over its recipes in the order of their starts. Raises where starts leave gaps."""
    def seal(t: pa.Table) -> pa.Table:
        t = t.sort_by([("start", "ascending")])
        doc, start, n, root = (t.column(c).to_pylist() for c in ("doc_id", "start", "n_tokens", "root"))
        if any(a + b != c for a, b, c in zip(start, n, start[1:], strict=False)):
            raise ValueError(f"recipes of part {t.column('part')[0]} do not follow one another")
        leaves = [address(repr((d, s, k)).encode() + r) for d, s, k, r in zip(doc, start, n, root, strict=True)]
        return pa.table({"part": t.column("part").slice(0, 1), "start": [start[0]], "docs": [len(t)], "ids": [sum(n)], "root": pa.array([merkle(leaves)], pa.binary())})

    return recipes.select("part", "doc_id", "start", "n_tokens", "root").groupBy("part").applyInArrow(seal, _PART)


def _head(manifest: DataFrame) -> DataFrame:
    """The one row that names a store, from its manifest, which has a row a part. Raises where parts leave gaps."""
    rows, at = manifest.orderBy("part").collect(), 0
    for r in rows:
        if r["start"] != at:
            raise ValueError(f"part {r['part']} begins at {r['start']}, not at {at}")
        at += r["ids"]
    head = [(len(rows), sum(r["docs"] for r in rows), at, bytearray(merkle([bytes(r["root"]) for r in rows])))]
    return manifest.sparkSession.createDataFrame(head, _HEAD)


# ---- reading ------------------------------------------------------------------------------

def _recipes(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("doc_id long, start long, n_tokens long, root binary, hashes binary, part int").parquet(f"{path}/recipes")


def _manifest(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(_PART).parquet(f"{path}/manifest")


def verify(spark: SparkSession, path: str) -> bytes:
    """The root that names the store; raises ValueError where the recipes are not those of the manifest, or the manifest not that of the head.

    A recipe that is missing, added, repeated, swapped with another or moved changes its part's root.
    """
    listed = _manifest(spark, path)
    mine, theirs = _sealed(_recipes(spark, path)), listed
    other = mine.exceptAll(theirs).unionByName(theirs.exceptAll(mine)).select("part").limit(1).collect()
    if other:
        raise ValueError(f"part {other[0][0]} of the recipes is not what the manifest says")
    head, stored = _head(listed).first(), spark.read.schema(_HEAD).parquet(f"{path}/head").collect()
    if stored != [head]:
        raise ValueError("the manifest is not the one that the head names")
    return bytes(head["root"])


def _chunks(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("hash binary, n int, payload binary, kind string").parquet(f"{path}/intake").where("kind = 'chunk'").drop("kind")


def _opened(h: bytes, n: int, payload: bytes, unpack) -> np.ndarray:
    """A chunk's ids; raises where they don't match their address."""
    raw = unpack.decompress(payload)
    if address(raw) != h:
        raise ValueError(f"chunk {h.hex()} does not hold what its address says")
    return np.frombuffer(raw, "<u2" if len(raw) == 2 * n else "<u4")


def _places(recipes: DataFrame) -> DataFrame:
    """(start, doc_id, n_tokens, root, pos, hash): a row for each chunk of each document."""
    at = F.sequence(F.lit(0), F.expr(f"int(length(hashes) div {ADDRESS}) - 1"))
    return recipes.select("start", "doc_id", "n_tokens", "root", F.explode(F.transform(at, lambda i: F.struct(i.alias("pos"), F.substring(F.col("hashes"), i * ADDRESS + 1, F.lit(ADDRESS)).alias("hash")))).alias("c")).select("start", "doc_id", "n_tokens", "root", "c.pos", "c.hash")


def read_digests(spark: SparkSession, path: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32, verified) for every document, from the files.

    The recipes are held against the manifest first. Each chunk is read once, unpacked and held against its address; a
    document is verified if its chunks are all there, their addresses give the root of its recipe and they hold as many ids as
    it says. Whatever fails raises ValueError. The ids' crc32 is taken as of little-endian unsigned 32-bit integers, joined
    from those of the chunks.
    """
    verify(spark, path)

    def digest(batches):
        unpack = zstandard.ZstdDecompressor()
        for b in batches:
            ids = [_opened(h, n, p, unpack) for h, n, p in zip(*(c.to_pylist() for c in b.columns), strict=True)]
            crcs = [zlib.crc32(x.astype("<u4").tobytes()) for x in ids]
            yield pa.record_batch([b.column(0), pa.array([len(x) for x in ids], pa.int32()), pa.array(crcs, pa.int64())], names=["hash", "n", "crc"])

    def whole(batches):
        for b in batches:
            doc, _, size, root, parts = (c.to_pylist() for c in b.columns)
            parts = [sorted(p, key=lambda x: x["pos"]) for p in parts]
            fine = [all(x["n"] is not None for x in p) and merkle([x["hash"] for x in p]) == r and sum(x["n"] for x in p) == k for p, r, k in zip(parts, root, size, strict=True)]
            if not all(fine):
                raise ValueError(f"document {doc[fine.index(False)]} can't be put together from its chunks")
            yield pa.record_batch(
                [b.column(0), b.column(1), b.column(2), pa.array([crc_joined([(x["crc"], 4 * x["n"]) for x in p]) for p in parts], pa.int64()), pa.array(fine)],
                names=["doc_id", "start", "n_tokens", "ids_crc32", "verified"],
            )

    chunks = _chunks(spark, path).mapInArrow(digest, "hash binary, n int, crc long")
    places = _places(_recipes(spark, path)).join(chunks, "hash", "left")
    docs = places.groupBy("start", "doc_id", "n_tokens", "root").agg(F.collect_list(F.struct("pos", "hash", "n", "crc")).alias("parts"))
    return docs.select("doc_id", "start", "n_tokens", "root", "parts").mapInArrow(whole, "doc_id long, start long, n_tokens long, ids_crc32 long, verified boolean")


def read_ids(spark: SparkSession, path: str, doc_ids: DataFrame | None = None) -> DataFrame:
    """(doc_id, start, ids array<int>): documents put together again, all or those of `doc_ids`."""
    def opened(batches):
        unpack = zstandard.ZstdDecompressor()
        for b in batches:
            ids = [_opened(h, n, p, unpack).astype(np.int32) for h, n, p in zip(*(c.to_pylist() for c in b.columns), strict=True)]
            yield pa.record_batch([b.column(0), pa.array(ids, pa.list_(pa.int32()))], names=["hash", "ids"])

    recipes = _recipes(spark, path)
    if doc_ids is not None:
        recipes = recipes.join(doc_ids.select("doc_id").distinct(), "doc_id", "left_semi")
    places = _places(recipes)
    chunks = _chunks(spark, path).join(places.select("hash").distinct(), "hash", "left_semi").mapInArrow(opened, "hash binary, ids array<int>")
    docs = places.join(chunks, "hash").groupBy("start", "doc_id").agg(F.array_sort(F.collect_list(F.struct("pos", "ids"))).alias("parts"))
    return docs.select("doc_id", "start", F.flatten(F.transform("parts", lambda p: p["ids"])).alias("ids"))
