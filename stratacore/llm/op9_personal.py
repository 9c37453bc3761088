"""Personal data: base patterns, and identifiers found by bootstrapped contexts.

The base patterns' matches in the corpus are the first seeds. Every seed, and every other identifier-like string with the
shape of a kind, stands in lexical patterns: the two words before it, and the word before it with the word after it.
Spark scores the graph of patterns and instances round by round, for each kind: a pattern's confidence is the summed
score of its instances over their number plus one (so that rare patterns stay weak); one of at least MIN_CONFIDENCE
with MIN_SEEDS different scored instances is trusted. Instances of trusted patterns are promoted: their score becomes
the best confidence around them, and in the next round they count as seeds, so that patterns in which no base match
ever stands can become trusted too. Scores only grow; a round that trusts no new pattern is the last, as is round
ROUNDS. Instances in trusted patterns are reported beside the base matches.

Edge cases: null or empty text: nothing found; instances never overlap base matches; rows are kept apart even when
repeated; very long texts are searched whole, by patterns without quadratic backtracking and by one merge of sorted
spans; context words are looked for within NEAR_CHARS characters; ties between kinds go by the order email, ip, card,
phone; empty table: empty result; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import shared_dir, written

KINDS = ("email", "ip", "card", "phone")
ROUNDS, MIN_CONFIDENCE, MIN_SEEDS = 8, 0.7, 3
_LOCAL = re.compile(r"[A-Za-z0-9._%+-]")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_ANY = re.compile(r"[0-9@]")
#: Identifier-like strings: address-like, colon groups, dotted numbers, digit groups.
_LIKE = re.compile(
    r"(?P<email>(?<![\w.@+-])[\w.%+-]{1,64}@[\w.-]{1,253}(?<![.-]))"
    r"|(?P<ip>(?<![\w:])(?:[0-9A-Fa-f]{1,4}:){2,7}:?[0-9A-Fa-f]{0,4}(?![\w:])|(?<![\w.])[0-9]{1,3}(?:\.[0-9]{1,3}){3}(?![\w.]*\w))"
    r"|(?P<digits>(?<![\w.,+-])\+?\(?[0-9](?:[ ().-]{0,2}[0-9]){6,18}(?![\w-]))"
)
_WORD_BEFORE = re.compile(r"(\w+)\W*$")
_WORD_AFTER = re.compile(r"\W*(\w+)")
NEAR_CHARS = 80


def _luhn(digits: str) -> bool:
    total = 0
    for k, d in enumerate(reversed(digits)):
        x = int(d) * (1 + k % 2)
        total += x - 9 * (x > 9)
    return total % 10 == 0


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind index, end) of the base matches, sorted."""
    out, done, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and _LOCAL.match(text, start - 1):
            start -= 1
        found = _DOMAIN.match(text, at + 1) if start < at else None
        if found:
            out.append((start, 0, found.end()))
            done = found.end()
        at = text.find("@", max(at + 1, done))
    out += [(m.start(), 1, m.end()) for m in _IP.finditer(text) if all(int(x[-4:]) <= 255 and len(x.lstrip("0")) <= 3 for x in m[0].split("."))]
    for m in _CARD.finditer(text):
        digits = m[0].replace(" ", "").replace("-", "")
        if 14 <= len(digits) <= 19 and _luhn(digits):
            out.append((m.start(), 2, m.end()))
    out += [(m.start(), 3, m.end()) for m in _PHONE.finditer(text) if 10 <= sum(c.isdigit() for c in m[0]) <= 15]
    return sorted(out)


def _contexts(text: str, start: int, end: int) -> list[str]:
    """The lexical patterns around a span; words are lower-cased, digits become 0."""
    plain = lambda w: re.sub(r"[0-9]", "0", w.lower())
    left = re.findall(r"\w+", text[max(0, start - NEAR_CHARS) : start])[-2:]
    after = _WORD_AFTER.match(text, end, end + NEAR_CHARS)
    out = []
    if len(left) == 2:
        out.append("2 " + " ".join(map(plain, left)))
    if left and after:
        out.append("1 " + plain(left[-1]) + " _ " + plain(after[1]))
    return out


def _like_kinds(m: re.Match) -> list[int]:
    if m.lastgroup != "digits":
        return [KINDS.index(m.lastgroup)]
    n = sum(c.isdigit() for c in m[0])
    return [k for k, fits in ((2, 13 <= n <= 19), (3, 7 <= n <= 15)) if fits]


def _occurrences(text: str, base: list[tuple[int, int, int]]) -> list[dict]:
    out = [{"kind": k, "seed": True, "start": a, "end": b, "value": text[a:b], "patterns": _contexts(text, a, b)} for a, k, b in base]
    taken, at, reach = sorted((a, b) for a, _, b in base), 0, 0
    for m in _LIKE.finditer(text):
        while at < len(taken) and taken[at][0] < m.end():  # matches come in order, so one pass over the spans does
            reach, at = max(reach, taken[at][1]), at + 1
        if reach <= m.start():
            near = _contexts(text, m.start(), m.end())
            out += [{"kind": k, "seed": False, "start": m.start(), "end": m.end(), "value": m[0], "patterns": near} for k in _like_kinds(m)]
    return out


_FOUND = "doc_id long, base array<struct<start: int, kind: int, end: int>>, seen array<struct<kind: int, seed: boolean, start: int, end: int, value: string, patterns: array<string>>>"


def _search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    span = pa.struct([("start", pa.int32()), ("kind", pa.int32()), ("end", pa.int32())])
    seen = pa.struct([("kind", pa.int32()), ("seed", pa.bool_()), ("start", pa.int32()), ("end", pa.int32()), ("value", pa.string()), ("patterns", pa.list_(pa.string()))])
    for b in batches:
        bases, occurrences = [], []
        for t in b.column(1).to_pylist():
            base = base_spans(t) if t and _ANY.search(t) else []
            bases.append([dict(zip(("start", "kind", "end"), x, strict=True)) for x in base])
            occurrences.append(_occurrences(t, base) if t and _ANY.search(t) else [])
        yield pa.RecordBatch.from_arrays([b.column(0), pa.array(bases, pa.list_(span)), pa.array(occurrences, pa.list_(seen))], ["doc_id", "base", "seen"])


def trusted_patterns(edges: DataFrame, rounds: int = ROUNDS, min_confidence: float = MIN_CONFIDENCE, min_seeds: int = MIN_SEEDS) -> DataFrame:
    """(kind, pattern, confidence) of the trusted patterns; edges: (kind, pattern, value, seed), distinct."""
    shared_dir(edges.sparkSession)
    edges = edges.checkpoint()
    scores, trusted, n = edges.withColumn("score", F.col("seed").cast("double")), None, -1
    for _ in range(rounds):
        rated = scores.groupBy("kind", "pattern").agg((F.sum("score") / (F.count(F.lit(1)) + 1)).alias("confidence"), F.count(F.when(F.col("score") > 0, 1)).alias("seeds"))
        trusted, before = rated.where((F.col("confidence") >= min_confidence) & (F.col("seeds") >= min_seeds)).drop("seeds").checkpoint(), n
        n = trusted.count()
        if n == before or n == 0:
            break
        promoted = edges.where(~F.col("seed")).join(trusted, ["kind", "pattern"]).groupBy("kind", "value").agg(F.max("confidence").alias("best"))
        scores = edges.join(promoted, ["kind", "value"], "left").select("kind", "pattern", "value", "seed", F.when(F.col("seed"), 1.0).otherwise(F.coalesce("best", F.lit(0.0))).alias("score"))
    return trusted


def personal_spans(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """(doc_id, base, extra): arrays of (start, kind, end) for every row; extra from trusted patterns."""
    rows = docs.select(F.col(id_column).cast("long").alias("doc_id"), F.col(text_column).cast("string").alias("text"))
    found = written(rows.mapInArrow(_search, _FOUND).withColumn("row", F.monotonically_increasing_id()), "personal")
    seen = found.where(F.size("seen") > 0).select("row", F.explode("seen").alias("s")).select("row", "s.*")
    edges = seen.select("kind", "value", "seed", F.explode("patterns").alias("pattern"))
    edges = edges.groupBy("kind", "pattern", "value").agg(F.max("seed").alias("seed"))
    good = trusted_patterns(edges)
    hits = seen.where(~F.col("seed")).select("row", "kind", "start", "end", F.explode("patterns").alias("pattern")).join(good, ["kind", "pattern"])
    one = hits.groupBy("row", "start", "end").agg(F.max_by("kind", F.struct("confidence", -F.col("kind"))).alias("kind"))
    extra = one.groupBy("row").agg(F.sort_array(F.collect_list(F.struct("start", "kind", "end"))).alias("extra"))
    return found.join(extra, "row", "left").select("doc_id", "base", F.coalesce("extra", F.expr("cast(array() as array<struct<start: int, kind: int, end: int>>)")).alias("extra"))


def _of_kind(k: int):
    return lambda s: s["kind"] == k


def personal_digests(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """(doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans); the counts are those of the base matches."""
    rows = personal_spans(docs, id_column, text_column)
    names = F.array(*[F.lit(k) for k in KINDS])
    joined = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))), ",")
    counts = [F.size(F.filter("base", _of_kind(k))).cast("long").alias(f"n_{KINDS[k]}") for k in range(4)]
    return rows.select("doc_id", *counts, F.sha2(joined(F.col("base")), 256).alias("base_sha256"), joined(F.sort_array(F.concat("base", "extra"))).alias("spans"))

