"""Byte-level BPE encoding and decoding in linear time.

A piece's bytes are read as Latin-1, so that an Aho-Corasick automaton of all tokens
finds the longest token at every place in one pass.  Encoding goes from left to
right with the longest token, and steps back to a shorter one where it does not fit its
neighbour.  Two tokens fit if merging their joint bytes by rank gives these two again; this
is decided from the halves that each token was merged from and memoised.  Every
place is entered once only, so the time is linear in the piece, and the ids are those of
merging pairs by rank.

Null texts are empty; empty texts have no ids.  Bytes that are no UTF-8 are
replaced by U+FFFD before encoding.  Ids are packed as little-endian unsigned 32-bit
integers.  Extra columns of the input pass through ``encode`` and ``decode``; a column that
already bears an output's name is replaced.
"""

from __future__ import annotations

import base64
import hashlib
from array import array
from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import as_bytes, fresh, map_arrow, read_table

#: Entries of a worker's memos; they are emptied when full, which costs time only.
MEMO = 400_000


def read_ranks(content: bytes) -> dict[bytes, int]:
    """Token bytes to rank, from the text of a ``.tiktoken`` file."""
    return {base64.b64decode(a): int(b) for a, b in map(bytes.split, content.splitlines()) if a}


class Memo(dict):
    """A bounded memo of a function of the key."""

    def __init__(self, make, most: int = MEMO):
        super().__init__()
        self.make, self.most = make, most

    def __missing__(self, key):
        if len(self) >= self.most:
            self.clear()
        value = self[key] = self.make(key)
        return value


class Codec:
    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import ahocorasick
        import regex

        self.ranks = ranks
        self.bytes_of = {i: t for t, i in ranks.items()}
        self.find = regex.compile(pattern).findall
        self.fits = Memo(self._fits)
        self.ids_of = Memo(self._pack)
        # for each token, the edge tokens met while it is merged, as (token, rank at which it is taken up)
        self.right_edge: dict[int, list[tuple[int, float]]] = {}
        self.left_edge: dict[int, list[tuple[int, float]]] = {}
        self.shorter: dict[int, int] = {}
        self.trie = ahocorasick.Automaton()
        for token, rank in sorted(ranks.items(), key=lambda x: x[1]):
            self.trie.add_word(token.decode("latin-1"), (rank, len(token)))
            self._split(token, rank)
        for token, rank in ranks.items():
            self.shorter[rank] = next((ranks[token[:n]] for n in range(len(token) - 1, 0, -1) if token[:n] in ranks), -1)
        self.fits.clear()
        self.trie.make_automaton()

    def _split(self, token: bytes, rank: int) -> None:
        never = float("inf")
        self.right_edge[rank], self.left_edge[rank] = [(rank, never)], [(rank, never)]
        for n in range(1, len(token)):
            a, b = self.ranks.get(token[:n], never), self.ranks.get(token[n:], never)
            if max(a, b) < rank and self._fits((a, b), rank):
                self.right_edge[rank] = [*self.right_edge[b][:-1], (b, rank), (rank, never)]
                self.left_edge[rank] = [*self.left_edge[a][:-1], (a, rank), (rank, never)]
                return

    def _fits(self, pair: tuple[int, int], below: float = float("inf")) -> bool:
        """Whether no merge of a rank under ``below`` crosses the border of the two tokens."""
        ours, theirs, name = self.right_edge[pair[0]], self.left_edge[pair[1]], self.bytes_of
        i = j = 0
        while True:
            (a, a_until), (b, b_until) = ours[i], theirs[j]
            joint = self.ranks.get(name[a] + name[b])
            if joint is not None and joint < below and joint < a_until and joint <= b_until:
                return False  # of equal ranks the leftmost merges first
            if i + 1 == len(ours) and j + 1 == len(theirs):
                return True
            if a_until <= b_until:
                i += 1
            else:
                j += 1

    def piece(self, raw: bytes) -> list[int]:
        """Ids of one piece."""
        whole = self.ranks.get(raw)
        if whole is not None:
            return [whole]
        n = len(raw)
        longest = [-1] * n
        for end, (rank, size) in self.trie.iter(raw.decode("latin-1")):
            longest[end - size + 1] = rank  # a later end is a longer token
        open_at = [True] * (n + 1)
        out, ends, at, fits, shorter, name = [], [], 0, self.fits, self.shorter, self.bytes_of
        token = longest[0]
        while at < n:
            stop = at + len(name[token])
            if open_at[stop] and (not out or fits[out[-1], token]):
                out.append(token)
                ends.append(stop)
                at = stop
                token = longest[at] if at < n else -1
                continue
            token = shorter[token]
            while token < 0:  # nothing fits here: this place is closed, and the token before is shortened
                open_at[at] = False
                token = shorter[out.pop()]
                ends.pop()
                at = ends[-1] if ends else 0
        return out

    def _pack(self, piece: str) -> bytes:
        return array("I", self.piece(piece.encode())).tobytes()

    def encode(self, text: str) -> bytes:
        """Packed ids of a whole text."""
        return b"".join(map(self.ids_of.__getitem__, self.find(text)))

    def decode(self, packed: bytes) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, array("I", packed)))


_CODECS: dict[bytes, Codec] = {}


def codec(content: bytes, pattern: str) -> Codec:
    """One codec for each vocabulary and worker."""
    key = hashlib.sha256(content + pattern.encode()).digest()
    if key not in _CODECS:
        _CODECS[key] = Codec(read_ranks(content), pattern)
    return _CODECS[key]


def default_vocabulary() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


def _ship(spark, path: str | None, pattern: str | None):
    known, usual = (path, pattern) if path and pattern else default_vocabulary()
    with open(path or known, "rb") as f:  # under 1 MB, read by the driver and sent to the workers
        return spark.sparkContext.broadcast((f.read(), pattern or usual))


def _extended(df: DataFrame, column: str, make, added: list[tuple[str, T.DataType]]) -> DataFrame:
    """The columns of ``df`` and those that make(values of ``column``) gives."""
    import pyarrow as pa
    from pyspark.sql.pandas.types import to_arrow_type

    names = [n for n, _ in added]
    kept = [c for c in df.columns if c not in names]
    types, source_name = [to_arrow_type(t) for _, t in added], fresh("_in", df.columns)

    def run(batches: Iterator):
        for batch in batches:
            made = make(batch.column(batch.schema.names.index(source_name)))
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(len(kept))), *(pa.array(v, t) for v, t in zip(made, types))], [*kept, *names])

    source = df.select(*[F.col(f"`{c}`") for c in kept], F.col(column).alias(source_name))
    schema = T.StructType([*(df.schema[c] for c in kept), *(T.StructField(n, t) for n, t in added)])
    return map_arrow(source, run, schema)


def encode(df: DataFrame, text: str = "text", path: str | None = None, pattern: str | None = None) -> DataFrame:
    """Adds ``ids`` (packed) and ``n_tokens``."""
    shipped = _ship(df.sparkSession, path, pattern)

    def make(column):
        c = codec(*shipped.value)
        ids = [c.encode(t.decode("utf-8", "replace")) for t in as_bytes(column)]
        return ids, [len(x) // 4 for x in ids]

    return _extended(df, text, make, [("ids", T.BinaryType()), ("n_tokens", T.LongType())])


def decode(df: DataFrame, ids: str = "ids", path: str | None = None, pattern: str | None = None) -> DataFrame:
    """Adds ``decoded``, the bytes of packed ids."""
    shipped = _ship(df.sparkSession, path, pattern)

    def make(column):
        c = codec(*shipped.value)
        return ([c.decode(x) for x in as_bytes(column)],)

    return _extended(df, ids, make, [("decoded", T.BinaryType())])


def token_digests(df: DataFrame, text: str = "text", path: str | None = None, pattern: str | None = None) -> DataFrame:
    """Encodes, decodes the ids again, and adds n_tokens and the digests of both, without moving ids to the JVM."""
    shipped = _ship(df.sparkSession, path, pattern)

    def make(column):
        c = codec(*shipped.value)
        sizes, ids_sha, decoded_sha = [], [], []
        for t in as_bytes(column):
            packed = c.encode(t.decode("utf-8", "replace"))
            sizes.append(len(packed) // 4)
            ids_sha.append(hashlib.sha256(packed).hexdigest())
            decoded_sha.append(hashlib.sha256(c.decode(packed)).hexdigest())
        return sizes, ids_sha, decoded_sha

    return _extended(df, text, make, [("n_tokens", T.LongType()), ("ids_sha256", T.StringType()), ("decoded_sha256", T.StringType())])


def op1_byte_bpe(spark, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    return token_digests(docs).select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256")
