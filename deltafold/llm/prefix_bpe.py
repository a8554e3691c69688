"""BPE encoding by dynamic programming over prefixes, and decoding.

Every prefix of a pretoken has one encoding, so one last token.  An automaton over the vocabulary gives the
tokens that end a prefix; the last token is the one among them that can stand after the last token of what
is left in front of it.  Following these tokens back from the whole pretoken gives its exact ids, without
merging anything.

Whether two tokens can stand side by side depends on their outer spines only: x on the right spine of the
left token and y on the left spine of the right one are neighbours until one of them is merged into its
parent, so the pair is split for good exactly if no rule joins any such x and y before that.  Of two equal
rules the left place is merged first.

Texts are cut at white space as the vocabulary's pattern does and the strings between are looked up in a
bounded memo, so only new ones are computed.

Cases: a null or empty text has no ids and decodes to the empty text; the vocabulary's special tokens in a
text become their ids, as the library does by default; texts and words may have any length; rows that repeat
are encoded as often as they occur; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
import re
from functools import lru_cache

import ahocorasick
import numpy as np
import public_tokenizers
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltafold.llm._common import Memo

# Fixed values of the byte-level vocabularies: white space, the pattern of pretokens, and the printable stand-ins of bytes.
_WS = r"\t-\r \x85\xa0  -     　"
_STRINGS = re.compile(rf" ?[^{_WS}]+|[{_WS}]+(?![^{_WS}])|[{_WS}]+")
_PRETOKENS = regex.compile(rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{_WS}\p{{L}}\p{{N}}]+|[{_WS}]+(?![^{_WS}])|[{_WS}]+")
_PLAIN = [*range(33, 127), *range(161, 173), *range(174, 256)]
_NEVER = 1 << 60


def _byte_of_char() -> dict[str, int]:
    others = [b for b in range(256) if b not in set(_PLAIN)]
    return {chr(b): b for b in _PLAIN} | {chr(256 + n): b for n, b in enumerate(others)}


class PrefixBpe:
    """Encoder and decoder of one byte-level BPE vocabulary file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        char = _byte_of_char()
        self.bytes_of: dict[int, bytes] = {i: bytes(char[c] for c in t) for t, i in spec["model"]["vocab"].items()}
        ids = spec["model"]["vocab"]
        self.rank: dict[tuple[int, int], int] = {}
        children: dict[int, tuple[int, int]] = {}
        made_at: dict[int, int] = {}
        for r, pair in enumerate(spec["model"]["merges"]):
            left, right = pair.split(" ") if isinstance(pair, str) else pair
            a, b, whole = ids[left], ids[right], ids[left + right]
            self.rank[a, b] = r
            if whole not in children:
                children[whole], made_at[whole] = (a, b), r
        # spines: (token, rank at which it is merged into the one above)
        self.right_spine = {t: self._spine(t, children, made_at, 1) for t in ids.values()}
        self.left_spine = {t: self._spine(t, children, made_at, 0) for t in ids.values()}
        self.special = {x["content"]: x["id"] for x in spec.get("added_tokens", [])}
        for text, i in self.special.items():
            self.bytes_of[i] = text.encode()
        self.split_special = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.automaton = ahocorasick.Automaton()
        for i in ids.values():
            key = self.bytes_of[i].decode("latin-1")
            if i not in self.special.values():
                self.automaton.add_word(key, (i, len(key)))
        self.automaton.make_automaton()
        self.fits: dict[int, bool] = {}
        self.pretokens = Memo(self._pretoken)
        self.strings = Memo(lambda s: b"".join(map(self.pretokens.__getitem__, _PRETOKENS.findall(s))))
        self.decimal = {i: str(i) for i in self.bytes_of}

    @staticmethod
    def _spine(token: int, children: dict, made_at: dict, side: int) -> list[tuple[int, int]]:
        out, until = [(token, _NEVER)], _NEVER
        while token in children:
            until = made_at[token]
            token = children[token][side]
            out.append((token, until))
        return out

    def side_by_side(self, left: int, right: int) -> bool:
        """Whether the two stay two tokens when their bytes are encoded together."""
        key = left << 32 | right
        got = self.fits.get(key)
        if got is None:
            rank = self.rank
            got = True
            for x, x_until in self.right_spine[left]:
                for y, y_until in self.left_spine[right]:
                    r = rank.get((x, y))
                    if r is not None and r < x_until and r <= y_until:
                        got = False
            if len(self.fits) > 1_000_000:
                self.fits.clear()
            self.fits[key] = got
        return got

    def _pretoken(self, word: str) -> bytes:
        data = word.encode("utf-8", "surrogatepass").decode("latin-1")
        last: list = [None] * (len(data) + 1)  # of each prefix: (last token, its length)
        fits, ok = self.fits.get, self.side_by_side
        for end, (token, size) in self.automaton.iter(data):
            end += 1
            if last[end] is None:
                start = end - size
                if start == 0:
                    last[end] = (token, size)
                else:
                    before = last[start][0]
                    known = fits(before << 32 | token)
                    if known or known is None and ok(before, token):
                        last[end] = (token, size)
        ids, at = [], len(data)
        while at:
            token, size = last[at]
            ids.append(token)
            at -= size
        return np.array(ids[::-1], "<u4").tobytes()

    def encode(self, text: str) -> bytes:
        """Ids as little-endian 32-bit bytes."""
        find, look = _STRINGS.findall, self.strings.__getitem__
        if self.split_special is None or not any(x in text for x in self.special):
            return b"".join(map(look, find(text)))
        parts = self.split_special.split(text)
        return b"".join(np.array([self.special[p]], "<u4").tobytes() if n % 2 else b"".join(map(look, find(p))) for n, p in enumerate(parts))

    def decode(self, ids: list[int]) -> str:
        return b"".join(map(self.bytes_of.__getitem__, ids)).decode("utf-8", "replace")


@lru_cache(maxsize=2)
def coder(path: str) -> PrefixBpe:
    return PrefixBpe(path)


_OUT = "doc_id long, n_tokens long, ids array<int>, ids_sha256 string, decoded string, decoded_sha256 string"
_OUT_ARROW = pa.schema([
    ("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids", pa.list_(pa.int32())), ("ids_sha256", pa.string()), ("decoded", pa.string()), ("decoded_sha256", pa.string()),
])


def _code(path: str, with_ids: bool, with_text: bool):
    def run(batches):
        bpe = coder(path)
        for batch in batches:
            cols: list[list] = [[] for _ in _OUT_ARROW.names]
            for key, text in zip(batch["id"].to_pylist(), batch["text"].to_pylist(), strict=True):
                ids = np.frombuffer(bpe.encode(text), "<u4").tolist()
                back = bpe.decode(ids)
                said = ",".join(map(bpe.decimal.__getitem__, ids))
                row = (key, len(ids), ids if with_ids else None, hashlib.sha256(said.encode()).hexdigest(), back if with_text else None, hashlib.sha256(back.encode()).hexdigest())
                for to, x in zip(cols, row, strict=True):
                    to.append(x)
            yield pa.record_batch(dict(zip(_OUT_ARROW.names, cols, strict=True)), schema=_OUT_ARROW)

    return run


def encoded_documents(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = True, with_text: bool = True) -> DataFrame:
    """Ids of every text, the text they decode to, and digests of both."""
    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    return texts.mapInArrow(_code(tokenizer_path, with_ids, with_text), _OUT)


def op10_bpe_codec(spark, sf_dir: str) -> DataFrame:
    """The encode-and-decode contract on ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = encoded_documents(docs, public_tokenizers.path("byte_bpe_50k.json"), with_ids=False, with_text=False)
    return out.select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256")
