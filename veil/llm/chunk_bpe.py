"""Byte-level BPE with content-defined chunk reuse.

A rolling hash cuts every text into chunks at places that depend on the content
only, so documents that share passages share chunks. A census of chunk digests
finds the shared ones and gives each an owner; the owner's document encodes it
once, other documents borrow its tokens. Where pieces meet, the tokens around
the joint are re-encoded in a window that grows until the window agrees with
the tokens on both of its rims, which makes the result exactly that of encoding
the whole text.

Why agreement is exact: no pretoken holds white space after another character,
and matching runs from left to right without looking back; so a token that
starts with white space after a token that ends in a visible ASCII byte
(an *anchor*) starts a pretoken in every context. A window from an anchor on
the left to an anchor on the right is encoded as in the whole text. A text
without anchors is re-encoded as a whole.

What moves: chunk digests (a few tens of bytes per chunk), the texts once, by
document, and tokens (two bytes each) of shared chunks and of the documents
that borrow. Chunks that very many documents share are fewer than a thousand:
their census rows and tokens (at most 16 KiB of text each) are broadcast and
join in place, so no task gathers a hot chunk. Plans are kept by document id and
text, so a plan holds the chunks of one text, also for null and repeated ids.

Defined results: null and empty texts have no tokens and the digests of the
empty string; repeated rows give repeated results, also with null ids; very
long texts stream through the same steps; ``<|endoftext|>`` in a text is the
special token, as the library has it by default; an empty table gives an empty
result; extra columns are ignored. Ids take two bytes where the vocabulary
allows it, else four.
"""

from __future__ import annotations

import base64
import functools
import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veil.operators.skew import hot_keys, join_hot
from veil.sources.shared import drop_written, in_arrow, materialize

#: Chunk sizes in bytes: at least, on average beyond that, at most.
LEAST, MEAN_BITS, MOST = 256, 10, 16_384
SPECIAL = "<|endoftext|>"
FINAL, OWNED, PART, BORROWED = 0, 1, 2, 3


def default_paths() -> tuple[str, str]:
    """The ranks and the JSON of the public vocabulary of 50k tokens."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.path("byte_bpe_50k.json")


@functools.lru_cache(2)
def _gear() -> np.ndarray:
    """256 odd-looking words from a splitmix sequence."""
    x = np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def chunk_ends(data: bytes) -> list[int]:
    """End offsets of the chunks of a UTF-8 text; every end is a character border."""
    n = len(data)
    if n <= LEAST:
        return [n] if n else []
    b = np.frombuffer(data, np.uint8)
    h = _gear()[b]
    for k in (1, 2, 4, 8, 16):
        h[k:] = h[k:] + (h[:-k] << np.uint64(k))
    marks = np.flatnonzero((h >> np.uint64(64 - MEAN_BITS)) == 0) + 1
    ends, last = [], 0
    for m in [*marks.tolist(), n]:
        while m - last > MOST:
            ends.append(last := _border(b, last + MOST))
        if m - last >= LEAST and m < n:
            ends.append(last := _border(b, m))
    if last < n:
        ends.append(n)
    return ends


def _border(b: np.ndarray, at: int) -> int:
    while at < len(b) and b[at] & 0xC0 == 0x80:
        at += 1
    return at


def _split(data: bytes) -> list[bytes]:
    out, start = [], 0
    for end in chunk_ends(data):
        if end > start:
            out.append(data[start:end])
        start = end
    return out


def digest(chunk: bytes) -> tuple[int, int]:
    d = xxhash.xxh3_128_digest(chunk)
    return int.from_bytes(d[:8], "little", signed=True), int.from_bytes(d[8:], "little", signed=True)


class Codec:
    """Exact whole-text encoder over one vocabulary; ``encode`` gives ids as unsigned numbers of ``kind``."""

    def __init__(self, ranks_path: str, json_path: str):
        import public_tokenizers
        import tiktoken
        from tokenizers import Tokenizer

        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(ranks_path, "rb"))}
        self.library = Tokenizer.from_file(json_path)
        self.library.no_padding()
        self.library.no_truncation()
        special = self.library.token_to_id(SPECIAL)
        self.fast = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={SPECIAL: special})
        self.bytes_of = [b""] * (max(special, max(ranks.values())) + 1)
        self.kind = np.uint16 if len(self.bytes_of) <= 1 << 16 else np.uint32
        for piece, i in ranks.items():
            self.bytes_of[i] = piece
        self.bytes_of[special] = SPECIAL.encode()
        self.starts_gap = np.array([p[:1] in (b" ", b"\n", b"\t", b"\r") for p in self.bytes_of])
        self.ends_visible = np.array([p[-1:].isascii() and b"!" <= p[-1:] <= b"~" for p in self.bytes_of])

    def encode(self, text: str) -> np.ndarray:
        try:
            ids = self.fast.encode_to_numpy(text, allowed_special={SPECIAL}, disallowed_special=())
        except BaseException as e:  # the fast library panics on some very long runs; the reference library does not
            if isinstance(e, (KeyboardInterrupt, SystemExit)):
                raise
            ids = np.array(self.library.encode(text, add_special_tokens=False).ids, dtype=np.uint32)
        return ids.astype(self.kind)

    def decode_bytes(self, ids: np.ndarray) -> bytes:
        table = self.bytes_of
        return b"".join([table[i] for i in ids.tolist()])

    def anchors(self, ids: np.ndarray) -> np.ndarray:
        """Indexes of tokens that start a pretoken in every context."""
        return np.flatnonzero(self.starts_gap[ids[1:]] & self.ends_visible[ids[:-1]]) + 1

    def stitch(self, pieces: list[np.ndarray]) -> np.ndarray:
        """Tokens of the whole text from the tokens of its consecutive pieces."""
        if not pieces:
            return np.zeros(0, self.kind)
        done: list[np.ndarray] = []
        left, k = pieces[0], 1
        while k < len(pieces):
            right = pieces[k]
            k += 1
            la, ra = self.anchors(left), self.anchors(right)
            while not len(la) and done:
                left = np.concatenate([done.pop(), left])
                la = self.anchors(left)
            held = [right]
            while not len(ra) and k < len(pieces):
                held.append(pieces[k])
                k += 1
                ra = self.anchors(np.concatenate([held[-2][-1:], held[-1]]))
                ra = ra + (sum(map(len, held[:-1])) - 1)
            right = np.concatenate(held) if len(held) > 1 else right
            start, window, end = self._repair(left, right, la, ra)
            done.append(left[:start])
            left = np.concatenate([window, right[end:]])
        return np.concatenate([*done, left])

    def _repair(self, left: np.ndarray, right: np.ndarray, la: np.ndarray, ra: np.ndarray) -> tuple[int, np.ndarray, int]:
        """Re-encode around the joint until the window agrees with the tokens on its rims."""
        depth = 1
        while True:
            inner = int(la[-depth]) if len(la) >= depth else 0
            outer = int(la[-depth - 1]) if len(la) > depth else 0
            near = int(ra[depth - 1]) if len(ra) >= depth else len(right)
            far = int(ra[depth]) if len(ra) > depth else near
            text = self.decode_bytes(np.concatenate([left[outer:], right[:far]])).decode("utf-8", "replace")
            ids = self.encode(text)
            rim_l, rim_r = left[outer:inner], right[near:far]
            whole = outer == 0 and far == len(right)
            fits = np.array_equal(ids[: len(rim_l)], rim_l) and (not len(rim_r) or np.array_equal(ids[-len(rim_r) :], rim_r))
            if fits or whole:
                return outer, ids, far
            depth += 1


@functools.lru_cache(2)
def codec(ranks_path: str, json_path: str) -> Codec:
    return Codec(ranks_path, json_path)


KEYS = "doc_id long, tk long, h1 long, h2 long"
PARTS = "kind byte, doc_id long, tk long, seq int, h1 long, h2 long, tokens binary, n_tokens long, ids_sha binary, text_sha binary"


def _texts(b: pa.RecordBatch) -> Iterator[tuple[int | None, int, bytes]]:
    col = b.column("text").cast(pa.binary())
    for i, tk, v in zip(b.column("doc_id").to_pylist(), b.column("tk").to_pylist(), col):
        yield i, tk, v.as_py() or b""


def _key_rows(batches: Iterator[pa.RecordBatch], schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rows: set[tuple] = set()
        for doc, tk, data in _texts(b):
            rows.update((doc, tk, *digest(c)) for c in _split(data))
        yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows) if rows else [[]] * 4, schema)], schema=schema)


class _Rows:
    """Collects rows of PARTS and cuts them into batches of bounded size."""

    def __init__(self, schema: pa.Schema):
        self.schema, self.rows, self.held = schema, [], 0

    def add(self, **row: object) -> None:
        self.rows.append(row)
        self.held += 200 + len(row.get("tokens") or b"")

    def full(self) -> bool:
        return self.held > 4 << 20

    def take(self) -> pa.RecordBatch:
        cols = [pa.array([r.get(f.name) for r in self.rows], f.type) for f in self.schema]
        self.rows, self.held = [], 0
        return pa.RecordBatch.from_arrays(cols, schema=self.schema)


def _final(c: Codec, ids: np.ndarray) -> dict:
    text = c.decode_bytes(ids).decode("utf-8", "replace")
    return {
        "n_tokens": len(ids),
        "ids_sha": hashlib.sha256(ids.astype("<u4").tobytes()).digest(),
        "text_sha": hashlib.sha256(text.encode("utf-8")).digest(),
    }


def _encode_rows(batches: Iterator[pa.RecordBatch], schema: pa.Schema, paths: tuple[str, str]) -> Iterator[pa.RecordBatch]:
    """Encode all that a document does not borrow; finish the documents that borrow nothing."""
    c = codec(*paths)
    out = _Rows(schema)
    for b in batches:
        plans = b.column("plan").to_pylist()
        for (doc, tk, data), plan in zip(_texts(b), plans):
            role = {(p["h1"], p["h2"]): p["own"] for p in plan or ()}
            pieces: list[tuple[tuple[int, int] | None, np.ndarray | None]] = []
            run: list[bytes] = []
            known: dict[tuple[int, int], np.ndarray] = {}

            def flush() -> None:
                if run:
                    pieces.append((None, c.encode(b"".join(run).decode("utf-8", "replace"))))
                    run.clear()

            for chunk in _split(data):
                h = digest(chunk) if role else None
                if h is None or h not in role:
                    run.append(chunk)
                    continue
                flush()
                if not role[h]:
                    pieces.append((h, None))
                    continue
                if h not in known:
                    known[h] = c.encode(chunk.decode("utf-8", "replace"))
                    out.add(kind=OWNED, h1=h[0], h2=h[1], tokens=known[h].tobytes())
                pieces.append((None, known[h]))
            flush()
            if all(p is not None for _, p in pieces):
                out.add(kind=FINAL, doc_id=doc, **_final(c, c.stitch([p for _, p in pieces])))
            else:
                for seq, (h, p) in enumerate(pieces):
                    if p is None:
                        out.add(kind=BORROWED, doc_id=doc, tk=tk, seq=seq, h1=h[0], h2=h[1])
                    else:
                        out.add(kind=PART, doc_id=doc, tk=tk, seq=seq, tokens=p.tobytes())
            if out.full():
                yield out.take()
    yield out.take()


def _assemble_rows(batches: Iterator[pa.RecordBatch], schema: pa.Schema, paths: tuple[str, str]) -> Iterator[pa.RecordBatch]:
    """Stitch the sorted parts of each document; rows come in the order document, text, position."""
    c = codec(*paths)
    out = _Rows(schema)
    key, pieces, copies = None, [], 0

    def close() -> None:
        if pieces:
            done = _final(c, c.stitch(pieces))
            for _ in range(copies):
                out.add(kind=FINAL, doc_id=key[0], **done)

    last = -1
    for b in batches:
        for doc, tk, seq, tokens in zip(*(b.column(n).to_pylist() for n in ("doc_id", "tk", "seq", "tokens"))):
            if (doc, tk) != key:
                close()
                key, pieces, copies, last = (doc, tk), [], 0, -1
            copies += seq == 0
            if seq != last:
                pieces.append(np.frombuffer(tokens, c.kind))
                last = seq
        if out.full():
            yield out.take()
    close()
    yield out.take()


def encode_documents(docs: DataFrame, paths: tuple[str, str] | None = None) -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256`` for every row of ``doc_id, text``."""
    paths = paths or default_paths()
    docs = docs.select("doc_id", "text", F.xxhash64(F.coalesce("text", F.lit(""))).alias("tk"))
    keys = materialize(in_arrow(docs, _key_rows, KEYS), "bpe-keys")
    owner = F.min(F.struct(F.col("doc_id").isNotNull().alias("k"), "doc_id", "tk"))
    census = keys.groupBy("h1", "h2").agg(F.count("*").alias("n"), owner.alias("o")).filter("n > 1")
    census = materialize(census, "bpe-census")
    chunk = ["h1", "h2"]
    hot = hot_keys(census, chunk, keys.count())
    own = F.col("doc_id").eqNullSafe(F.col("o.doc_id")) & (F.col("tk") == F.col("o.tk"))
    plans = (
        join_hot(keys, census.drop("n"), chunk, hot)
        .groupBy(F.col("doc_id").alias("__d"), F.col("tk").alias("__t"))
        .agg(F.collect_set(F.struct("h1", "h2", own.alias("own"))).alias("plan"))
    )
    planned = docs.join(plans, (F.col("tk") == F.col("__t")) & F.col("doc_id").eqNullSafe(F.col("__d")), "left").select("doc_id", "text", "tk", "plan")
    parts = materialize(in_arrow(planned, _encode_rows, PARTS, paths), "bpe-parts")
    drop_written(keys, census)
    tokens = parts.filter(F.col("kind") == OWNED).groupBy("h1", "h2").agg(F.first("tokens").alias("tokens"))
    tokens = materialize(tokens, "bpe-tokens")
    place = ["doc_id", "tk", "seq"]
    asking = parts.filter(F.col("kind") == BORROWED).select(*place, "h1", "h2")
    borrowed = join_hot(asking, tokens, chunk, hot).select(*place, "tokens")
    waiting = parts.filter(F.col("kind") == PART).select(*place, "tokens").unionByName(borrowed)
    sorted_parts = waiting.repartition("doc_id", "tk").sortWithinPartitions(*place)
    joined = in_arrow(sorted_parts, _assemble_rows, PARTS, paths)
    final = ["doc_id", "n_tokens", "ids_sha", "text_sha"]
    done = parts.filter(F.col("kind") == FINAL).select(*final).unionByName(joined.select(*final))
    return done.select("doc_id", "n_tokens", F.lower(F.hex("ids_sha")).alias("ids_sha256"), F.lower(F.hex("text_sha")).alias("decoded_sha256"))
