"""Secrets in texts: all rules in one automaton, one pass over the bytes of each text."""

from __future__ import annotations

from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cubelens.llm.arrow import map_rows, texts
from cubelens.llm.automaton import PatternSet


def _either(word: str) -> str:
    return "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in word)


@dataclass(frozen=True)
class Rule:
    """A kind of secret; ``least`` bounds the match, or what follows its shortest match less one character."""

    kind: str
    pattern: str
    least: int = 0
    tail: bool = False


_KEYWORDS = "|".join(map(_either, ("password", "passwd", "secret", "token"))) + "|" + _either("api") + "_?" + _either("key")
#: A private key from its BEGIN line to its END line; what stands between has no other dashes
#: in a row. Without an END line: header lines, runs of base64 between blanks, line ends
#: (escaped ones too) and signs of quoting, and a last run that is padded or starts a line.
_KEY_LINE = "[A-Z ]*PRIVATE KEY-----"
_GAP = "([\\x20\\x09\\x0a\\x0d\"'>#*,;]|\\\\[nrt])"
_CUT_KEY = f"({_GAP}+(Proc-Type|DEK-Info):[^\\x0a\\x0d\\\\]*)*({_GAP}+\\+?{_GAP}*[A-Za-z0-9+/]{{16,}}=?=?)*({_GAP}+[A-Za-z0-9+/]+==?|(\\x0a|\\\\n)[A-Za-z0-9+/]+)?"
_WHOLE_KEY = f"(-?-?-?-?[A-Za-z0-9+/=:,._()\"'>#*;\\\\\\x20\\x09\\x0a\\x0d])*-----END {_KEY_LINE}"
#: The three base rules come first; spans sort by start, then in this order.
RULES = (
    Rule("assign", f"({_KEYWORDS})[\"']?\\x20*[:=]\\x20*[\"']?[A-Za-z0-9+/_.=-]+", 6, True),
    Rule("access", "AKIA[A-Z0-9]+", 20),
    Rule("hex", "[0-9a-f]{24,}", 24),
    Rule("private_key", f"-----BEGIN {_KEY_LINE}({_WHOLE_KEY}|{_CUT_KEY})?"),
    Rule("web_token", "eyJ[A-Za-z0-9_-]+\\.[A-Za-z0-9_-]+\\.[A-Za-z0-9_-]+", 40),
    Rule("forge_token", "gh[pousr]_[A-Za-z0-9]+", 40),
    Rule("chat_token", "xox[abprs]-[A-Za-z0-9-]+", 20),
    Rule("map_key", "AIza[A-Za-z0-9_-]+", 39),
    Rule("payment_key", "[sr]k_live_[A-Za-z0-9]+", 24),
    Rule("url_login", "(https?|ftp|postgres|mysql|mongodb|redis|amqp)://[A-Za-z0-9._-]+:[A-Za-z0-9._!$%*+=-]+@"),
)
BASE_KINDS = ("assign", "access", "hex")
MASK = "[SECRET]"
SPANS = "array<struct<kind:string,start:bigint,end:bigint>>"


def compile_rules(rules: tuple[Rule, ...] = RULES) -> PatternSet:
    return PatternSet([r.pattern for r in rules])


def spans_of(text: str | None, machine: PatternSet, rules: tuple[Rule, ...] = RULES) -> list[tuple[str, int, int]]:
    """(kind, start, end) in code points, end exclusive, by start, then in the order of the rules."""
    data = (text or "").encode("utf-8", "surrogatepass")
    found = []
    for k, start, end, first in machine.find(data):
        if (end - first + 1 if rules[k].tail else end - start) >= rules[k].least:
            found.append((start, k, end))
    if found and len(data) != len(text):
        found = [(len(data[:a].decode("utf-8", "surrogatepass")), k, len(data[:b].decode("utf-8", "surrogatepass"))) for a, k, b in found]
    return [(rules[k].kind, a, b) for a, k, b in sorted(found)]


def find_secrets(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """(doc_id, spans): one row per row of ``docs``; spans is an array of (kind, start, end).

    A null text counts as empty; doc_id may be null or repeat; other columns are not read.
    Matches of one rule never overlap; those of different rules may.
    """
    machine = compile_rules(rules)

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        spans = [[{"kind": k, "start": a, "end": b} for k, a, b in spans_of(t, machine, rules)] for t in texts(part.column(1))]
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))
        return pa.record_batch([part.column(0).cast(pa.int64()), pa.array(spans, kind)], ["doc_id", "spans"])

    return map_rows(docs.select("doc_id", "text"), run, f"doc_id long, spans {SPANS}")


def spans_digest(spans: Column) -> Column:
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))))


def secret_report(docs: DataFrame) -> DataFrame:
    """Counts and digests of the spans of ``find_secrets``, one row per row of ``docs``."""
    base = F.filter("spans", lambda s: s["kind"].isin(*BASE_KINDS))
    count = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return find_secrets(docs).select("doc_id", *map(count, BASE_KINDS), F.sha2(spans_digest(base), 256).alias("base_sha256"), spans_digest(F.col("spans")).alias("spans"))


def mask_secrets(docs: DataFrame, rules: tuple[Rule, ...] = RULES, mask: str = MASK) -> DataFrame:
    """``docs`` with every span replaced by ``mask`` in ``text`` and ``n_chars`` brought in line.

    Overlapping spans are masked as one. Texts without secrets, nulls included, stay as they
    are; every row and column stays.
    """
    machine, names = compile_rules(rules), docs.columns
    at = names.index("text")

    def run(part: pa.RecordBatch) -> pa.RecordBatch:
        old = part.column(at).to_pylist()
        new = []
        for t in old:
            done, pieces = 0, []
            for _, a, b in spans_of(t, machine, rules):
                if a >= done:
                    pieces += [t[done:a], mask]
                done = max(done, b)
            new.append("".join([*pieces, t[done:]]) if pieces else t)
        columns = list(part.columns)
        columns[at] = pa.array(new, columns[at].type)
        if "n_chars" in names:
            k = names.index("n_chars")
            columns[k] = pa.array([n if a is b else len(b) for a, b, n in zip(old, new, columns[k].to_pylist())], columns[k].type)
        return pa.RecordBatch.from_arrays(columns, schema=part.schema)

    return map_rows(docs, run, docs.schema)
