"""Quality rules with tokeniser fertility.

Base rules count words, symbols, repeated lines and repeated 5-word windows. The method then encodes
every word with a public vocabulary and measures characters per token, the share of byte-fallback
tokens and the entropy of the tokens, each held against a band of the document's language, or of its
main script where the language has none.

Null or empty texts: no words, all counts 0, base_failed (fewer than 10 words). Repeated doc_ids: one
row each. Extra columns are ignored by `quality` and kept by `keep_good`.
"""

from __future__ import annotations

from array import array
from dataclasses import dataclass
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut_up, documents, kept_in_worker, small_batches, words_of

#: The symbols that count.
SYMBOLS = "#*$%&|<>"
SCHEMA = (
    "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, "
    "base_failed boolean, kept boolean, n_tokens long, chars_per_token double, byte_share double, entropy double, band string"
)


@dataclass(frozen=True)
class Band:
    """Bounds of the fertility measures; outside one, the document is rejected."""

    chars_low: float
    chars_high: float
    byte_high: float
    entropy_low: float


#: By language, else by script. The vocabulary was made mostly from English, so others get fewer characters a token.
#: The lower bounds of the four languages lie just below the given tables' running text, whose 1st percentiles are 1.94 (en),
#: 1.80 (fr), 1.99 (de) and 1.80 (es); random letters reach 1.64, random consonants 1.50, encoded bytes 1.26. The other bands are
#: not measured on text.
BANDS = {
    "en": Band(1.65, 8.0, 0.10, 2.0),
    "fr": Band(1.52, 8.0, 0.10, 2.0),
    "de": Band(1.52, 8.0, 0.10, 2.0),
    "es": Band(1.52, 8.0, 0.10, 2.0),
    "latin": Band(1.3, 8.0, 0.15, 2.0),
    "cyrillic": Band(0.9, 6.0, 0.20, 2.0),
    "greek": Band(0.6, 6.0, 0.60, 2.0),
    "cjk": Band(0.3, 4.0, 0.75, 2.0),
    "other": Band(0.2, 8.0, 0.98, 1.5),
}
#: First and last code point of the scripts' main blocks.
SCRIPTS = (("latin", 0x41, 0x24F), ("greek", 0x370, 0x3FF), ("cyrillic", 0x400, 0x52F), ("cjk", 0x3040, 0x9FFF), ("cjk", 0xAC00, 0xD7AF))
#: A word's tokens are kept for reuse up to this length, so many at most.
CACHED_CHARS, CACHED_WORDS, CHUNK = 40, 100_000, 200


def main_script(text: str) -> str:
    if text.isascii():
        return "latin"
    points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    points = points[(points > 0x40) & ~((points > 0x5A) & (points < 0x61))]
    n = {}
    for name, a, b in SCRIPTS:
        n[name] = n.get(name, 0) + int(((points >= a) & (points <= b)).sum())
    best = max(n, key=n.get)
    return best if n[best] * 2 >= max(1, len(points)) else "other"


def repeated_words(words: list[str], n: int = 5) -> int:
    """How many words stand in an n-word window that the text holds twice or more."""
    m = len(words) - n + 1
    if m < 2:
        return 0
    with np.errstate(over="ignore"):  # windows that differ under a hash differ; most texts end here
        mixed = np.fromiter(map(hash, words), np.int64, len(words)).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        mixed ^= mixed >> np.uint64(29)
        rolled = mixed[:m].copy()
        for k in range(1, n):
            rolled = rolled * np.uint64(0xD6E8FEB86659FD93) + mixed[k : k + m]
    rolled.sort()
    if not (rolled[1:] == rolled[:-1]).any():
        return 0
    index: dict[str, int] = {}
    ids = np.fromiter((index.setdefault(w, len(index)) for w in words), np.int64, len(words))
    names = ids
    for k in range(1, n):  # pairs (name of the first k words, next word) get new dense names: exact, no hashing
        key = names[: len(ids) - k] * len(index) + ids[k:]
        if k < n - 1 and int(names.max()) < 2**62 // max(1, len(index) ** 2):
            names = key
            continue
        names = np.unique(key, return_inverse=True)[1]
    count = np.bincount(names)
    twice = np.flatnonzero(count[names] > 1)
    if not len(twice):
        return 0
    edge = np.zeros(len(words) + 1, np.int64)
    np.add.at(edge, twice, 1)
    np.add.at(edge, twice + n, -1)
    return int((np.cumsum(edge) > 0).sum())


class Fertility:
    """Tokens of single words under one vocabulary with byte fallback."""

    def __init__(self, path: str):
        import sentencepiece

        self.model = sentencepiece.SentencePieceProcessor(model_file=path)
        size = self.model.get_piece_size()
        self.fallback = np.fromiter((self.model.is_byte(i) for i in range(size)), bool, size)
        self.cache: dict[str, bytes] = {}

    def tokens(self, lists: list[list[str]]) -> list[np.ndarray]:
        """Token ids of each list of words; words new to the cache are encoded in one call."""
        if len(self.cache) > CACHED_WORDS:
            self.cache.clear()
        cache = self.cache
        unknown = [w for w in set().union(*lists) if w not in cache]
        long: list[str] = []
        for w, ids in zip(unknown, self.model.encode(unknown, num_threads=1) if unknown else ()):
            cache[w] = array("H", ids).tobytes()
            if len(w) > CACHED_CHARS:
                long.append(w)
        out = [np.frombuffer(b"".join(map(cache.__getitem__, words)), np.uint16) for words in lists]
        for w in long:
            del cache[w]
        return out


def judge_all(texts: list, langs: list, model: Fertility, bands=BANDS) -> list[tuple]:
    """All of SCHEMA but doc_id, for many texts."""
    out: list[tuple] = []
    for i in range(0, len(texts), CHUNK):
        lists = [words_of(t or "") for t in texts[i : i + CHUNK]]
        out += map(judge, texts[i : i + CHUNK], langs[i : i + CHUNK], lists, model.tokens(lists), repeat(model.fallback), repeat(bands))
    return out


def judge(text: str | None, lang: str | None, words: list[str], ids: np.ndarray, fallback: np.ndarray, bands: dict) -> tuple:
    text = text or ""
    n = len(words)
    chars = sum(map(len, words))
    symbols = sum(map(text.count, SYMBOLS))
    seen: set[str] = set()
    again = 0
    for line in text.split("\n"):
        if line in seen:
            again += 1
        elif line.strip(" \t\n\x0b\x0c\r"):
            seen.add(line)
    again_words = repeated_words(words)
    failed = n < 10 or 100 * again_words > 20 * n
    name = lang if lang in bands else main_script(text)
    band = bands[name]
    if not len(ids):
        return n, chars, symbols, again, again_words, failed, False, 0, None, None, None, name
    count = np.bincount(ids)
    count = count[count > 0] / len(ids)
    per, share, entropy = chars / len(ids), float(fallback[ids].mean()), float(-(count * np.log2(count)).sum())
    good = band.chars_low <= per <= band.chars_high and share <= band.byte_high and entropy >= band.entropy_low
    return n, chars, symbols, again, again_words, failed, good and not failed, len(ids), per, share, entropy, name


def vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def _mapper(path: str, bands: dict, carry: list[str] | None):
    def run(batches):
        model = kept_in_worker(f"fertility {path}", lambda: Fertility(path))
        for b in cut_up(batches):
            texts = b.column("text").to_pylist()
            langs = b.column("lang").to_pylist()
            out = judge_all(texts, langs, model, bands)
            if carry is not None:
                yield b.filter(pa.array([r[6] for r in out], pa.bool_()))
                continue
            cols = list(zip(*out)) or [()] * 12
            kinds = [pa.int64()] * 5 + [pa.bool_()] * 2 + [pa.int64()] + [pa.float64()] * 3 + [pa.string()]
            names = [x.split()[0] for x in SCHEMA.split(", ")]
            yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), *(pa.array(c, k) for c, k in zip(cols, kinds))], names=names)

    return run


def quality(docs: DataFrame, model_path: str | None = None, bands: dict | None = None) -> DataFrame:
    """Counts, fertility and verdict of each document (doc_id, text, lang)."""
    small_batches(docs.sparkSession)
    docs = docs.select("doc_id", "text", "lang")
    return docs.mapInArrow(_mapper(model_path or vocabulary(), bands or BANDS, None), SCHEMA)


def keep_good(docs: DataFrame, model_path: str | None = None, bands: dict | None = None) -> DataFrame:
    """The documents that the rules keep, with all their columns."""
    small_batches(docs.sparkSession)
    return docs.mapInArrow(_mapper(model_path or vocabulary(), bands or BANDS, docs.columns), docs.schema)


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality(documents(spark, sf_dir)).withColumns({c: F.round(c, 6) for c in ("chars_per_token", "byte_share", "entropy")})
