"""Token ids of texts by a public tokenizer, with a bounded table of words already encoded.

A tokenizer that works like the default one (KNOWN) drops white space and never joins text across
it, so the ids of a text are the ids of its pieces between ASCII white space, in order. Distinct
pieces are encoded by the tokenizers library: words of letters many at a time, others alone. Any
other tokenizer gets whole texts. Ids are 16-bit, little-endian; larger vocabularies are refused.
"""

from __future__ import annotations

import json
import os
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from bitparse.llm.common import as_bytes, fresh, give_back

END, KEPT_WORDS, LONGEST = 1, 500_000, 64
#: Words of letters that stay letters in lower case and in every normal form.
_LETTERS = re.compile(rb"(?:[A-Za-z]|\xc3[\x80-\x96\x98-\xb6\xb8-\xbf])+")
#: 1: a letter; 2: the second byte of one; 3: a mark; 4: white space.
_KIND = np.zeros(256, np.uint8)
_KIND[[*range(65, 91), *range(97, 123)]] = 1
_KIND[[k for k in range(0x80, 0xC0) if k not in (0x97, 0xB7)]] = 2
_KIND[list(b".,;:!?")] = 3
_KIND[list(b" \t\n\r\x0b\x0c")] = 4


#: How a tokenizer must normalise and cut texts for its words to be encoded apart.
KNOWN = {
    "normalizer": {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}, {"type": "Lowercase"}]},
    "pre_tokenizer": {"type": "Sequence", "pretokenizers": [{"type": "Split", "pattern": {"Regex": r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"}, "behavior": "Removed", "invert": True}, {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False}]},
}


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class Encoder:
    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer
        from tokenizers.pre_tokenizers import WhitespaceSplit

        self.tokenizer = Tokenizer.from_file(path)
        self.plain = Tokenizer(self.tokenizer.model)  # for words of lower-case ASCII letters, which are their own normal form
        self.plain.pre_tokenizer = WhitespaceSplit()
        vocabulary = self.tokenizer.get_vocab()
        made = json.loads(self.tokenizer.to_str())
        self.by_word = all(made[k] == v for k, v in KNOWN.items()) and made["model"]["end_of_word_suffix"] == "</w>"
        if max(vocabulary.values()) >= 1 << 16:
            raise ValueError("ids are kept in 16 bits; the vocabulary is larger")
        self.ends = np.zeros(1 << 16, bool)  # ids that end a word
        self.ends[[k for piece, k in vocabulary.items() if piece.endswith("</w>")]] = True
        self.known: dict[bytes, bytes] = {}
        self.older: dict[bytes, bytes] = {}

    def _each(self, words: list[bytes]) -> list[bytes]:
        return [np.array(e.ids, np.uint16).tobytes() for e in self.tokenizer.encode_batch_fast([w.decode("utf-8", "replace") for w in words], add_special_tokens=False)]

    def _together(self, words: list[bytes], tokenizer) -> list[bytes]:
        """The ids of words of letters, each of which the tokenizer takes as one word: all in one text, cut where words end."""
        ids = np.array(tokenizer.encode_batch_fast([b" ".join(words).decode()], add_special_tokens=False)[0].ids, np.uint16)
        cut = (2 * (np.flatnonzero(self.ends[ids]) + 1)).tolist()
        if len(cut) != len(words):
            return self._each(words)
        raw = ids.tobytes()
        return [raw[a:b] for a, b in zip([0, *cut], cut, strict=False)]

    def _learn(self, missing: set[bytes]) -> dict[bytes, bytes]:
        """The ids of words that are not in the table; words of letters go there, and others that are not long."""
        found: dict[bytes, bytes] = {}
        plain, letters, other = [], [], []
        older = self.older.get
        for w in missing:
            if (ids := older(w)) is not None:
                found[w] = ids
            elif w.isalpha() and w.islower() and len(w) <= LONGEST:
                plain.append(w)
            elif len(w) <= LONGEST and _LETTERS.fullmatch(w):
                letters.append(w)
            elif len(w) <= LONGEST:
                other.append(w)
            else:
                self.passing[w] = self._each([w])[0]
        for words, tokenizer in ((plain, self.plain), (letters, self.tokenizer)):
            for lo in range(0, len(words), 4000):
                part = words[lo : lo + 4000]
                found.update(zip(part, self._together(part, tokenizer), strict=True))
        found.update(zip(other, self._each(other), strict=True))
        self.known.update(found)
        return found

    def texts(self, raw: list[bytes | None]) -> list[bytes]:
        """The ids of each text, without an end."""
        if not self.by_word:
            return self._each([x or b"" for x in raw])
        if len(self.known) > KEPT_WORDS:
            self.older, self.known = self.known, {}
        get, self.passing = self.known.get, {}
        split = [x.split() for x in spaced(raw)]
        ids = [list(map(get, own)) for own in split]
        gaps = [[k for k, x in enumerate(own) if x is None] if None in own else () for own in ids]
        found = self._learn({own[k] for own, at in zip(split, gaps, strict=True) for k in at})
        found.update(self.passing)
        for own, out, at in zip(split, ids, gaps, strict=True):
            for k in at:
                out[k] = found[own[k]]
        return [b"".join(own) for own in ids]


def spaced(raw: list[bytes | None]) -> list[bytes]:
    """The texts in lower-case ASCII, with a space before each single mark that follows a letter and ends a word.

    The tokenizer makes the mark a word of its own, so the ids stay the same, and fewer words differ.
    Texts that may hold a special token keep their case.
    """
    plain = [x.lower() if x and b"<|" not in x else x or b"" for x in raw]
    a = np.frombuffer(b" ".join([b" ", *plain, b" "]), np.uint8)
    kind = _KIND[a]
    letter = (kind[1:-2] == 1) | ((a[:-3] == 0xC3) & (kind[1:-2] == 2))
    at = np.flatnonzero(letter & (kind[2:-1] == 3) & (kind[3:] == 4)) + 2
    out = np.insert(a, at, 32).tobytes()
    ends = np.cumsum([2, *(len(x) + 1 for x in plain)])
    ends += np.searchsorted(at, ends)
    return [out[lo:hi] for lo, hi in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)]


_encoders: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    if path not in _encoders:
        _encoders.clear()
        _encoders[path] = Encoder(path)
    return _encoders[path]


def release() -> None:
    """Gives back the table of words of this worker, for operators that come after and hold tables of their own."""
    _encoders.clear()
    give_back()


def crc(ids: np.ndarray) -> int:
    return zlib.crc32(ids.astype("<u4").tobytes())


def tokenize(df: DataFrame, path: str | None = None, text: str = "text", keep: tuple[str, ...] = ("doc_id",), tally: bool = False, hold: bool = True) -> DataFrame:
    """The kept columns, ``ids`` (16-bit, the end id last) and ``n``, their number. A null text counts as empty.

    With ``tally`` there is one row more for each partition, with no ids, n of 0 and the counts of all
    ids of the partition in a column of that name, which is null elsewhere. Without ``hold`` workers give
    back their table of words after each partition, for jobs whose other stages need the memory.
    """
    path = path or default_path()
    body = fresh(df, "body")
    own = df.select(*keep, F.col(text).alias(body))
    kept = own.drop(body).schema
    schema = T.StructType([*(T.StructField(f.name, f.dataType) for f in kept), *T.StructType.fromDDL("ids binary, n long" + ", tally binary" * tally)])
    end = np.array([END], np.uint16).tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, total, part = encoder(path), np.zeros(1 << 16, np.int64), None
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                ids = [x + end for x in own.texts(as_bytes(part[body]))]
                columns = [*(part[k] for k in keep), pa.array(ids, pa.binary()), pa.array([len(x) // 2 for x in ids], pa.int64())]
                if tally:
                    columns.append(pa.nulls(part.num_rows, pa.binary()))
                    total += np.bincount(np.frombuffer(b"".join(ids), np.uint16), minlength=1 << 16)
                yield pa.RecordBatch.from_arrays(columns, schema.names)
        if not hold:
            release()
        if tally and part is not None:
            yield pa.RecordBatch.from_arrays([*(pa.nulls(1, part[k].type) for k in keep), pa.array([b""]), pa.array([0], pa.int64()), pa.array([total.astype("<i8").tobytes()])], schema.names)

    return own.mapInArrow(run, schema)
