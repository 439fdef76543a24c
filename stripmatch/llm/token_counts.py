"""Token counts by the whole-token shortcut.

Offline proof: a vocabulary string is a *whole token* when the library's merges, run on it alone as one pre-token,
end in that one token. A pre-token equal to a proven string costs one look-up; the others go through the merges.
Counts add up over pieces cut at ASCII white space, because the pre-tokens of this family of tokenizers never span
white space and its normalizer acts within such a piece; so each distinct piece is counted once per worker and kept
in a table of bounded size.

Defined cases: null or empty text has 0 tokens and 0 bytes; repeated rows are counted each; strings of added special
tokens inside a text count as the library's default does; extra columns are dropped; an empty table gives no rows.
"""

from __future__ import annotations

import json
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from tokenizers import Tokenizer
from tokenizers.pre_tokenizers import ByteLevel

from stripmatch.cluster import ship
from stripmatch.llm.textnp import chunks

KEPT = 400_000
LONG = 256  # bytes; longer pieces are not kept, so the tables' memory is bounded
#: The pre-tokenizer's pattern, on lower-case ASCII without white space. Fixed value.
_ASCII = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-z]+|[0-9]|[^a-z0-9]+")
_counters: dict[str, "WholeTokenCounter"] = {}


class WholeTokenCounter(dict):
    """piece (bytes without ASCII white space) -> tokens; missing pieces are worked out."""

    def __init__(self, path: str):
        super().__init__()
        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        suffix = spec["model"].get("end_of_word_suffix") or ""
        if "'s|'t|'re|'ve|'m|'ll|'d|" not in json.dumps(spec["pre_tokenizer"]) or not any(n.get("type") == "Lowercase" for n in spec["normalizer"]["normalizers"]):
            raise ValueError("the shortcut is proved for lower-casing tokenizers with this pre-token pattern only")
        self.special = [t["content"].encode() for t in spec.get("added_tokens", [])]
        self.model, self.normalizer, self.pre = self.tokenizer.model, self.tokenizer.normalizer, self.tokenizer.pre_tokenizer
        self.whole = self.proven(spec["model"]["vocab"], suffix)
        self.before: dict[bytes, int] = {}
        self.merged: dict[str, int] = {}
        pre = ByteLevel(add_prefix_space=False, use_regex=False)
        self.byte_char = {b: None for b in range(256)}
        for b in range(128):
            self.byte_char[b] = pre.pre_tokenize_str(chr(b))[0][0]
        for b in (0xC2, 0xC3):
            for t in range(0x80, 0xC0):
                self.byte_char[b], self.byte_char[t] = pre.pre_tokenize_str(bytes([b, t]).decode())[0][0]

    def proven(self, vocab: dict[str, int], suffix: str) -> frozenset[str]:
        """Vocabulary strings, without the word-end mark, that as one pre-token give exactly themselves."""
        found = []
        for s, i in vocab.items():
            if suffix and not s.endswith(suffix):
                continue
            bare = s[: len(s) - len(suffix)] if suffix else s
            if bare and [t.id for t in self.model.tokenize(bare)] == [i]:
                found.append(bare)
        return frozenset(found)

    def pretoken(self, text: str) -> int:
        """text: a pre-token as the model sees it."""
        if text in self.whole:
            return 1
        n = self.merged.get(text)
        if n is None:
            if len(text) > LONG:
                return len(self.model.tokenize(text))
            if len(self.merged) >= KEPT:
                self.merged.clear()
            n = self.merged[text] = len(self.model.tokenize(text))
        return n

    def __missing__(self, piece: bytes) -> int:
        n = self.before.get(piece)
        if n is None:
            n = self.worked_out(piece)
        if len(piece) > LONG:
            return n
        if len(self) >= KEPT:  # two generations: frequent pieces stay
            self.before = dict(self)
            self.clear()
        self[piece] = n
        return n

    def worked_out(self, piece: bytes) -> int:
        low = piece.lower()
        if piece.isascii() and b"<|" not in piece:
            if low.isalpha():  # one run of letters is one pre-token
                return self.pretoken(low.decode())
            return sum(map(self.pretoken, _ASCII.findall(low.decode())))
        text = piece.decode()
        if any(s in piece for s in self.special):
            return len(self.tokenizer.encode(text, add_special_tokens=False).ids)
        if text.isalpha() and max(text) < "\u0130":  # Latin-1 letters: composed, one pre-token, lower case letter by letter
            return self.pretoken("".join(map(self.byte_char.__getitem__, text.lower().encode())))
        text = self.normalizer.normalize_str(text)
        return sum(self.pretoken(t) for t, _ in self.pre.pre_tokenize_str(text))

    def count(self, text: bytes) -> int:
        return sum(map(self.__getitem__, text.split()))


def counter(path: str) -> WholeTokenCounter:
    if path not in _counters:
        _counters[path] = WholeTokenCounter(path)
    return _counters[path]


def count_tokens(docs: DataFrame, tokenizer_path: str, limit: int = 2048, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, n_bytes, n_tokens, over_limit. tokenizer_path must be readable on every worker."""
    ship(docs.sparkSession)
    narrow = docs.select(docs[id_col].alias("doc_id"), docs[text_col].alias("text"))

    def run(batches):
        of = counter(tokenizer_path)
        for batch in batches:
            tokens, size = np.zeros(batch.num_rows, np.int64), np.zeros(batch.num_rows, np.int64)
            for c in chunks(batch.column(1)):
                raw = c.b.tobytes()
                for i in range(c.n):
                    s, e = int(c.off[i]), int(c.off[i + 1])
                    tokens[c.lo + i], size[c.lo + i] = of.count(raw[s:e]), e - s
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(size), pa.array(tokens), pa.array(tokens > limit)], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return narrow.mapInArrow(run, f"doc_id {dict(narrow.dtypes)['doc_id']}, n_bytes long, n_tokens long, over_limit boolean")
