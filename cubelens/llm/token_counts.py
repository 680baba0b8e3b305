"""Token counts of a word-level BPE vocabulary, with a shortcut for words that are one token.

Offline, every vocabulary string that ends a word is encoded alone; those that come back as
one token with their own id are proven whole. A text is cut into pre-tokens; a proven one
counts as one token, the others are merged once each and remembered. The cutting is done
here only for characters for which a probe of the library shows the same folding and the
same cuts. Cuts never span white space, so texts are counted stretch by stretch between
blanks, and stretches are remembered; one that holds any other character, or an added token's
string, is merged by the library on its own.
"""

from __future__ import annotations

import re
import unicodedata
from functools import lru_cache
from pathlib import Path

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from tokenizers import Tokenizer

from cubelens.llm.arrow import map_rows, texts

VOCABULARY = "word_bpe_49k.json"
LIMIT = 2048
#: Characters that the probe tries: alphabets, punctuation and symbols up to kana, ideographs, syllables, wide forms, pictographs.
PROBED = (range(0x3100), range(0x4E00, 0xA000), range(0xAC00, 0xD7A4), range(0xFF00, 0xFFF0), range(0x1F300, 0x1FB00))
#: Never tried: marks join with what stands before them, and so do the parts of Hangul syllables.
_JOINS = ("M", "Cs", "Cn")
_HANGUL_PARTS = range(0x1100, 0x1200)
#: Stretches up to this length are remembered.
SHORT = 64
#: Stretches, and merged pre-tokens, that a task remembers; a memory is emptied when full.
REMEMBERED = 300_000
_CUT = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|\p{L}+|\p{N}|[^\s\p{L}\p{N}]+")
_CUT_SPACE = regex.compile(r"\s")
_END = "</w>"


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(VOCABULARY)


def _byte_letters() -> dict[str, int]:
    """The printable stand-ins of bytes in a byte-level vocabulary, by rule: printable Latin-1 stand for themselves."""
    own = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in own]
    return {chr(b): b for b in own} | {chr(256 + k): b for k, b in enumerate(rest)}


def whole_words(tokenizer: Tokenizer) -> frozenset[str]:
    """Pre-tokens that encode alone as one token, proven by encoding each."""
    letters, words, ids = _byte_letters(), [], []
    for piece, number in tokenizer.get_vocab().items():
        stem = piece.removesuffix(_END)
        if stem != piece and stem and all(c in letters for c in stem):
            try:
                words.append(bytes(letters[c] for c in stem).decode("utf-8"))
                ids.append(number)
            except UnicodeDecodeError:
                continue
    done = tokenizer.encode_batch(words, add_special_tokens=False)
    return frozenset(w for w, k, e in zip(words, ids, done) if e.ids == [k])


def safe_characters(tokenizer: Tokenizer, candidates=PROBED) -> str:
    """Candidates that the library folds and cuts as this module does, alone and between letters, digits and signs."""
    fold, cut, safe = tokenizer.normalizer.normalize_str, tokenizer.pre_tokenizer.pre_tokenize_str, []
    inner = _byte_letters()
    for code in (x for r in candidates for x in r):
        c = chr(code)
        if unicodedata.category(c).startswith(_JOINS) or code in _HANGUL_PARTS:
            continue
        probe = f"{c} a{c}b 1{c}2 !{c}?  {c} {c}{c} '{c}s a'{c} \u00e9{c} {c}"
        if c.isspace() != bool(_CUT_SPACE.match(c)):
            continue
        if [bytes(inner[x] for x in piece) for piece, _ in cut(fold(probe))] == [w.encode() for w in _CUT.findall(probe.lower())]:
            safe.append(c)
    return "".join(safe)


def _ranges(characters: str) -> str:
    """The inside of a character class, runs of neighbours as ranges."""
    codes, out, at = sorted(map(ord, characters)), [], 0
    while at < len(codes):
        end = at
        while end + 1 < len(codes) and codes[end + 1] == codes[end] + 1:
            end += 1
        out.append(f"{re.escape(chr(codes[at]))}-{re.escape(chr(codes[end]))}")
        at = end + 1
    return "".join(out)


@lru_cache(maxsize=4)
def proof(tokenizer_json: str) -> tuple[frozenset[str], str]:
    """Words proven whole and characters proven safe: done once, by the driver."""
    library = Tokenizer.from_str(tokenizer_json)
    return whole_words(library), safe_characters(library)


class Counter:
    """Token counts of texts, equal to the library's."""

    def __init__(self, tokenizer_json: str, limit: int = REMEMBERED, proven: tuple[frozenset[str], str] | None = None):
        self.library = Tokenizer.from_str(tokenizer_json)
        self.library.no_truncation()
        self.library.no_padding()
        self.whole, safe = proven or proof(tokenizer_json)
        added = "".join(f"|{re.escape(t.content)}" for t in self.library.get_added_tokens_decoder().values())
        other = f"(?:[^{_ranges(safe)}]{added})"
        self.odd = re.compile(other)
        self.stretch = re.compile(rf"[^ \t\n\r\f\v]*?{other}[^ \t\n\r\f\v]*")
        self.limit, self.known, self.merged = limit, {}, {}
        letter = {b: c for c, b in _byte_letters().items()}
        self.letters = [letter[b] for b in range(256)]
        self.tokenize = self.library.model.tokenize

    def _encode(self, text: str) -> int:
        return len(self.library.encode(text, add_special_tokens=False).ids)

    def _merge(self, word: str) -> int:
        """Tokens of a pre-token: the library's merges of its bytes' letters."""
        if not (word.isascii() and word.isprintable()):
            word = "".join([self.letters[b] for b in word.encode()])
        return len(self.tokenize(word))

    def _remember(self, memory: dict[str, int], word: str, n: int) -> int:
        if len(word) <= SHORT:
            if len(memory) >= self.limit:
                memory.clear()
            memory[word] = n
        return n

    def _stretch(self, stretch: str) -> int:
        """Tokens of a stretch of safe characters without blanks: its pre-tokens that are proven whole count one, the rest is merged."""
        n = 0
        for w in _CUT.findall(stretch):
            if w in self.whole:
                n += 1
            else:
                k = self.merged.get(w)
                n += self._remember(self.merged, w, self._merge(w)) if k is None else k
        return self._remember(self.known, stretch, n)

    def count(self, text: str) -> int:
        n, known = 0, self.known
        if self.odd.search(text):
            for stretch in self.stretch.findall(text):
                k = known.get(stretch)
                n += self._remember(known, stretch, self._encode(stretch)) if k is None else k
            text = self.stretch.sub(" ", text)
        for stretch in text.lower().split():
            k = known.get(stretch)
            n += self._stretch(stretch) if k is None else k
        return n


@lru_cache(maxsize=4)
def _counter(tokenizer_json: str, proven: tuple[frozenset[str], str]) -> Counter:
    return Counter(tokenizer_json, proven=proven)


def count_tokens(docs: DataFrame, path: str | None = None, limit: int = LIMIT) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit), one row per row of ``docs``.

    A null text counts as empty. The vocabulary file is read by the driver from ``path`` and
    goes to the tasks with the function. Whole texts are counted: nothing is cut off or
    filled up. Repeated rows and null doc_ids are kept; other columns are not read.
    """
    tokenizer_json = Path(path or default_path()).read_text()
    proven = proof(tokenizer_json)

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        counter, rows = _counter(tokenizer_json, proven), texts(part.column(1))
        n = [counter.count(t) for t in rows]
        return pa.record_batch(
            [part.column(0).cast(pa.int64()), pa.array([len(t.encode("utf-8", "surrogatepass")) for t in rows], pa.int64()), pa.array(n, pa.int64()), pa.array([k > limit for k in n], pa.bool_())],
            ["doc_id", "n_bytes", "n_tokens", "over_limit"],
        )

    return map_rows(docs.select("doc_id", "text"), run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
