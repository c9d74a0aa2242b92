"""Exact byte-level BPE encoding by dynamic programming over prefixes, and decoding.

Method. A byte string has one encoding only, and each of its prefixes has one last token: the token that ends there,
starts where a shorter prefix ends, and is compatible with that prefix's own last token. Two tokens are compatible if
merging their joined bytes by rank gives the two back. Tokens that end at a position are found by walking left as long
as the bytes read are a suffix of some token: the automaton of all tokens' suffixes, held as a table from suffix to the token
it is, if any, with one byte more to the left as its transition. Following the
stored last tokens backwards yields the ids. Encodings of recurring pre-tokens are kept in a bounded two-generation memo.

Edge cases. Null counts as the empty text (no tokens). Added special tokens in a text become their ids, as the
tokenizers library does. Very long texts are cut into pre-tokens, and a long pre-token is worked off prefix by prefix, in
time linear in its length for the tokens' bounded length. An empty table gives an empty table. Repeated rows give repeated
results; other columns, of any names, are not read.
"""

from __future__ import annotations

import json
from functools import lru_cache
from struct import pack

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import small_batches

#: The published byte-level pre-token pattern (fixed value).
PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
#: Memo entries in a generation; code points of a block of a long text.
MEMO, BLOCK = 200_000, 1 << 20


def _byte_letters() -> dict[str, int]:
    """Printable stand-ins of the 256 bytes in the vocabulary file: printable Latin-1 stands for itself, the rest follow from 256."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(own)]
    return {chr(b): b for b in own} | {chr(256 + i): b for i, b in enumerate(rest)}


class _Memo(dict):
    """Packed ids by pre-token; when a generation is full, entries unused since the one before go."""

    def __init__(self, encode):
        super().__init__()
        self.encode, self.old = encode, {}

    def __missing__(self, pre: str) -> bytes:
        found = self.old.get(pre)
        if found is None:
            found = pack("<%dI" % len(t), *t) if (t := self.encode(pre.encode("utf-8", "surrogatepass"))) else b""
        self[pre] = found
        return found

    def bounded(self) -> _Memo:
        if len(self) > MEMO:
            self.old = dict(self)
            self.clear()
        return self


class Encoder:
    """Encoder and decoder of one vocabulary file in the tokenizers format."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        letters = _byte_letters()
        raw = {t: bytes(letters[c] for c in t) for t in spec["model"]["vocab"]}
        ids = spec["model"]["vocab"]
        pairs = (m.split(" ") if isinstance(m, str) else m for m in spec["model"]["merges"])
        self.rank = {(ids[a], ids[b]): (r, ids[a + b]) for r, (a, b) in enumerate(pairs)}
        self.single = {b: ids[c] for c, b in letters.items() if c in ids}
        self.bytes_of = {ids[t]: b for t, b in raw.items()}
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.bytes_of |= {i: t.encode() for t, i in self.special.items()}
        self.fit: dict[int, bool] = {}
        self.last_step: dict[int, tuple[int, int, int]] = {}
        self.lefts: dict[int, list] = {}
        self.rights: dict[int, list] = {}
        # Suffixes of tokens: the token's id if the suffix is a token that merging can reach, else -1.
        self.ends: dict[bytes, int] = {}
        for t, b in raw.items():
            for k in range(len(b)):
                self.ends.setdefault(b[k:], -1)
        for t, b in raw.items():
            if self.merge([self.single[x] for x in b]) == [ids[t]]:
                self.ends[b] = ids[t]
                if self.step:
                    self.last_step[ids[t]] = self.step
        self.split = regex.compile(PATTERN).findall
        self.cut = regex.compile(r"\S(?=\s)")
        self.mark = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.memo = _Memo(self.word)

    def merge(self, t: list[int]) -> list[int]:
        """Merge the bytes of one token by rank, noting its last merge."""
        rank = self.rank
        self.step = None
        while len(t) > 1:
            best = min(((rank[p][0], i) for i, p in enumerate(zip(t, t[1:])) if p in rank), default=None)
            if best is None:
                break
            i = best[1]
            self.step = (best[0], t[i], t[i + 1])
            t[i : i + 2] = [rank[t[i], t[i + 1]][1]]
        return t

    def edge(self, t: int, side: int) -> list[tuple[int, float]]:
        """Tokens that stand at one edge (0 left, 1 right) while the token is merged, each with the rank that takes it up."""
        found, taken = [], float("inf")
        while True:
            found.append((t, taken))
            step = self.last_step.get(t)
            if step is None:
                return found
            taken, t = step[0], step[1 + side]

    def compatible(self, a: int, b: int) -> bool:
        key = a << 32 | b
        found = self.fit.get(key)
        if found is None:
            if len(self.fit) > 500_000:
                self.fit.clear()
            # A merge across the border happens before either neighbour is taken up; of equal ranks the left place is first.
            rank, rights = self.rank.get, self.lefts.get(b)
            if rights is None:
                rights = self.lefts[b] = self.edge(b, 0)
            lefts = self.rights.get(a)
            if lefts is None:
                lefts = self.rights[a] = self.edge(a, 1)
            found = self.fit[key] = not any((r := rank((x, y))) is not None and r[0] < tx and r[0] <= ty for x, tx in lefts for y, ty in rights)
        return found

    def word(self, data: bytes) -> list[int]:
        """Ids of one pre-token: the last token of every prefix, then the way back."""
        ends, fit, compatible = self.ends.get, self.fit.get, self.compatible
        whole = ends(data)
        if whole is not None and whole >= 0:
            return [whole]
        last, length = [-1] * (len(data) + 1), [0] * (len(data) + 1)
        for i in range(1, len(data) + 1):
            j = i - 1
            while (t := ends(data[j:i])) is not None:
                if t >= 0:
                    known = True if j == 0 else fit(last[j] << 32 | t)
                    if known or known is None and compatible(last[j], t):  # the only one, so no other need be tried
                        last[i], length[i] = t, i - j
                        break
                j -= 1
        out, i = [], len(data)
        while i:
            out.append(last[i])
            i -= length[i]
        return out[::-1]

    def _plain(self, text: str, out: list[bytes]) -> None:
        at = 0
        while at < len(text):
            end = len(text)
            # A block may end before a blank that follows a non-blank: no pre-token crosses that place.
            if end - at > BLOCK and (m := self.cut.search(text, at + BLOCK)):
                end = m.end()
            memo = self.memo.bounded()
            out.extend([memo[w] for w in self.split(text[at:end])])
            at = end

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        out: list[bytes] = []
        for piece in self.mark.split(text) if self.mark and any(s in text for s in self.special) else (text,):
            if piece in self.special:
                out.append(int(self.special[piece]).to_bytes(4, "little"))
            elif piece:
                self._plain(piece, out)
        return b"".join(out)

    def decode(self, ids: bytes) -> str:
        return b"".join(map(self.bytes_of.__getitem__, np.frombuffer(ids, "<u4").tolist())).decode("utf-8", "replace")


@lru_cache(2)
def encoder(path: str) -> Encoder:
    return Encoder(path)


def default_path() -> str:
    import public_tokenizers

    return str(public_tokenizers.path("byte_bpe_50k.json"))


def encode_decode(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None) -> DataFrame:
    """Per document: ``id_col``, n_tokens, ids (binary, little-endian unsigned 32-bit), decoded (text of the ids)."""
    small_batches(docs.sparkSession)
    path = path or default_path()

    def run(batches):
        e = encoder(path)
        for b in batches:
            ids = [e.encode(t or "") for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array(ids, pa.binary()), pa.array(map(e.decode, ids), pa.string())],
                names=[id_col, "n_tokens", "ids", "decoded"],
            )

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col), F.col(text_col).cast("string")).mapInArrow(run, f"`{id_col}` {kind}, n_tokens long, ids binary, decoded string")
