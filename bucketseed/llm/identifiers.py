"""PII: fixed kinds by their form, and further identifiers by bootstrapped contexts.

Emails, addresses, cards and phones are found by form (the base), and they and long hexadecimal
keys are the seed entities. A lexical pattern is what stands around a token: two words before it,
or one on either side, with its quotes and the classes of its characters. Spark scores the graph of
patterns and instances (distinct values) by turns: a pattern's confidence is the share of known
entities of one kind among its instances; an instance joins a kind when its confident patterns,
taken together, leave little doubt. Turns go on until no instance joins. Tokens without digits are
judged by slots, the patterns without classes: the slots that known entities mostly fill are looked
up in all texts, every token in them counts against them, and a token that joins is known from then
on. The confident patterns are then applied to every text. A form that failed its check (a digit run
that is no card, say) counts against its patterns and is never added.

A pattern needs ``support`` different known entities, at every size of the corpus. An instance is
one token between white space, without quotes and punctuation at its ends, of any length; a value
of several tokens is found only by the base forms. Defined results: null text is empty; texts are
read whole; repeated rows give a row each, and repeated values count once in the graph; a score
exactly at a limit passes; added spans never overlap base ones; of kinds with equal doubt the first
by name wins; other columns, also those named like the results, are carried or replaced; an empty
table has no patterns.
"""

from __future__ import annotations

import re
from bisect import bisect_left, bisect_right
from dataclasses import dataclass

import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bucketseed.staging import counted

KINDS = ("email", "ip", "card", "phone")
ADDED = "secret"

# Fixed forms. A local part is read back from its @, and runs of digits are entered only at their
# start, so that no text takes time that grows with the square of a run.
DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
ADDRESS = re.compile(r"(?<![0-9])[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
KEY = re.compile(r"(?=[0-9a-fA-F]*[0-9])(?=[0-9a-fA-F]*[a-fA-F])[0-9a-fA-F]{32,128}\Z")
DIGIT = re.compile(r"[0-9]")
EDGES = "\"'`()[]{}<>.,;:!?#*$%&|"
TOKEN = re.compile(r"[^\x20\x09-\x0D]+")
#: Of a token that an entity is cut from, the context is the nearest so many characters.
TOUCHING = 24


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = int(d) * (1 + i % 2)
        total += n - 9 if n > 9 else n
    return total % 10 == 0


def _inside(text: str, start: int, end: int) -> bool:
    """Whether a letter or digit touches text[start:end], as in a longer key."""
    return text[max(start - 1, 0) : start].isalnum() or text[end : end + 1].isalnum()


def base_spans(text: str) -> tuple[list[tuple[int, int, int]], list[tuple[int, int]]]:
    """(start, end, kind number) of the base in order, and spans of matches that failed a check."""
    good, bad = [], []
    at, done = text.find("@"), 0
    while at >= 0:
        start = at
        while start > done and text[start - 1] in LOCAL:
            start -= 1
        m = DOMAIN.match(text, at + 1) if start < at else None
        if m:
            good.append((start, m.end(), 0))
            done = m.end()
        else:
            done = max(done, at + 1)
        at = text.find("@", max(done, at + 1))
    if DIGIT.search(text):
        for m in ADDRESS.finditer(text):
            ok = all(int(p) <= 255 for p in m.group().split(".") if len(p) < 20) and all(
                len(p.lstrip("0")) <= 3 for p in m.group().split(".")
            )
            good.append((*m.span(), 1)) if ok else bad.append(m.span())
        for m in CARD.finditer(text):
            digits = m.group().replace(" ", "").replace("-", "")
            ok = 12 <= len(digits) <= 19 and luhn(digits)
            if ok:
                good.append((*m.span(), 2))
            elif 12 <= len(digits) <= 19 and not _inside(text, *m.span()):
                bad.append(m.span())
        for m in PHONE.finditer(text):
            ok = 9 <= sum(c in "0123456789" for c in m.group()) <= 15
            good.append((*m.span(), 3)) if ok else bad.append(m.span())
    return sorted(good, key=lambda s: (s[0], s[2])), bad


class Tokens:
    """A text's runs between white space, for looking up what stands around a place."""

    def __init__(self, text: str):
        self.text = text
        self.spans = [m.span() for m in TOKEN.finditer(text)]
        self.starts = [s for s, _ in self.spans]

    def at(self, place: int) -> int:
        """The number of the token that holds the character at ``place``."""
        return bisect_right(self.starts, place) - 1

    def word(self, i: int, low: int = 0, high: int | None = None) -> str:
        """Token i between ``low`` and ``high``, folded; of a cut token the nearest characters."""
        if not 0 <= i < len(self.spans):
            return ""
        s, e = self.spans[i]
        if s < low:
            s, e = low, min(e, low + TOUCHING)
        if high is not None and e > high:
            s, e = max(s, high - TOUCHING), high
        return DIGIT.sub("9", self.text[s:e].lower())

    def around(self, start: int, end: int) -> tuple[str, str, str]:
        """The two words before ``start`` and the one after ``end``, parts of a token included."""
        i = bisect_left(self.starts, start) - 1
        j = bisect_right(self.starts, end - 1) - 1
        if j >= 0 and self.spans[j][1] <= end:
            j += 1
        return self.word(i - 1), self.word(i, high=start), self.word(j, low=end)

    def trimmed(self, i: int) -> tuple[int, int]:
        """Token i without quotes and punctuation at its ends."""
        s, e = self.spans[i]
        while s < e and self.text[s] in EDGES:
            s += 1
        while e > s and self.text[e - 1] in EDGES:
            e -= 1
        return s, e


def _key(*parts: str) -> int:
    return xxhash.xxh64_intdigest("\0".join(parts)) - (1 << 63)


def _patterns(text: str, start: int, end: int, near: tuple[str, str, str], quotes: tuple[str, str]) -> list[int]:
    """Hashes of what stands around text[start:end], with the classes of its characters."""
    value = text[start:end]
    classes = "".join(
        c
        for c, there in (
            ("9", DIGIT.search(value) is not None),
            ("a", any(x.isalpha() for x in value)),
            ("@", "@" in value),
            (".", "." in value),
        )
        if there
    )
    return [_key("two", near[0], near[1], quotes[0], classes), _key("both", near[1], *quotes, near[2], classes)]


def _slots(near: tuple[str, str, str], quotes: tuple[str, str]) -> list[int]:
    """The same without the value's classes; a place with nothing before it is none."""
    if not near[1]:
        return []
    return [_key("slot two", near[0], near[1], quotes[0]), _key("slot both", near[1], *quotes, near[2])]


class Taken:
    """Whether a token touches one of some spans."""

    def __init__(self, spans: list[tuple[int, int]]):
        self.starts, self.ends = [], []
        for s, e in sorted(spans):
            if self.ends and s < self.ends[-1]:
                self.ends[-1] = max(self.ends[-1], e)
            else:
                self.starts.append(s)
                self.ends.append(e)

    def touches(self, start: int, end: int) -> bool:
        i = bisect_left(self.starts, end)
        return i > 0 and self.ends[i - 1] > start


def instances(text: str, good: list, bad: list) -> list[tuple]:
    """Base spans and tokens with a digit: (start, end, seed kind or None, whether it may be added,
    patterns, slots, word before)."""
    found, tokens = [], Tokens(text)

    def add(start, end, seed, free, i):
        left, right = tokens.spans[i]
        near = tokens.around(start, end) if not free else (tokens.word(i - 2), tokens.word(i - 1), tokens.word(i + 1))
        quotes = (text[max(left, start - 2) : start], text[end : min(end + 1, right)]) if free else ("", "")
        slots = []
        if free or tokens.trimmed(i) == (start, end):
            own = (tokens.word(i - 2), tokens.word(i - 1), tokens.word(i + 1))
            slots = _slots(own, (text[max(left, start - 2) : start], text[end : min(end + 1, right)]))
        found.append((start, end, seed, free, _patterns(text, start, end, near, quotes), slots, tokens.word(i - 1) if slots else ""))

    for s, e, k in good:
        add(s, e, KINDS[k], False, tokens.at(s))
    for s, e in bad:
        add(s, e, None, False, tokens.at(s))
    taken = Taken([(s, e) for s, e, _ in good] + bad)
    m = DIGIT.search(text)
    while m:
        i = tokens.at(m.start())
        left, right = tokens.spans[i]
        start, end = tokens.trimmed(i)
        if start < end and not taken.touches(left, right):
            add(start, end, ADDED if KEY.match(text[start:end]) else None, True, i)
        m = DIGIT.search(text, right)
    return found


def slot_instances(text: str, taken: Taken, words: frozenset[str]) -> list[tuple[int, int, list[int]]]:
    """(start, end, slots) of the tokens without digits that stand after one of ``words``."""
    before = TOKEN.findall(DIGIT.sub("9", text.lower()))
    after = [i for i, w in enumerate(before[:-1], 1) if w in words]
    found = []
    if after:
        tokens = Tokens(text)
        for i in after:
            left, right = tokens.spans[i]
            start, end = tokens.trimmed(i)
            if start < end and not DIGIT.search(text, start, end) and not taken.touches(left, right):
                near = (tokens.word(i - 2), tokens.word(i - 1), tokens.word(i + 1))
                quotes = (text[max(left, start - 2) : start], text[end : min(end + 1, right)])
                found.append((start, end, _slots(near, quotes)))
    return found


def _texts(batches, text: str, every: bool = False):
    """(batch, texts that may hold identifiers or None) row by row; null is empty."""
    for batch in batches:
        col = batch.column(batch.schema.get_field_index(text)).cast(pa.large_string()).fill_null("")
        maybe = pc.match_substring_regex(col, "." if every else "[0-9@]")
        yield batch, [t.as_py() if m.as_py() else None for t, m in zip(col, maybe, strict=True)]


def _inst(value: str) -> int:
    return xxhash.xxh64_intdigest(value.lower()) - (1 << 63)


def pattern_graph(docs: DataFrame, text: str = "text") -> tuple[DataFrame, DataFrame, DataFrame]:
    """Distinct (pattern, inst), distinct (pattern, inst, before) of slots, and (inst, kind) of seeds."""

    def run(batches):
        for _, texts in _texts(batches, "text"):
            inst, kind, patterns, slots, words = [], [], [], [], []
            for t in texts:
                if t is None:
                    continue
                for s, e, seed, _, keys, own, before in instances(t, *base_spans(t)):
                    inst.append(_inst(t[s:e]))
                    kind.append(seed)
                    patterns.append(keys)
                    slots.append(own)
                    words.append(before)
            keys = pa.list_(pa.int64())
            yield pa.RecordBatch.from_arrays(
                [pa.array(inst, pa.int64()), pa.array(kind, pa.string()), pa.array(patterns, keys), pa.array(slots, keys), pa.array(words, pa.string())],
                ["inst", "kind", "patterns", "slots", "before"],
            )

    rows, _ = counted(
        docs.select(F.col(text).alias("text"))
        .mapInArrow(run, "inst bigint, kind string, patterns array<bigint>, slots array<bigint>, before string")
        .distinct(),
        "instances",
    )
    edges, _ = counted(rows.select(F.explode("patterns").alias("pattern"), "inst").distinct(), "edges")
    slots, _ = counted(rows.select(F.explode("slots").alias("pattern"), "inst", "before").distinct(), "slots")
    seeds, _ = counted(rows.filter("kind IS NOT NULL").select("inst", "kind").distinct(), "seeds")
    return edges, slots, seeds


def slot_graph(docs: DataFrame, wanted: dict[int, str], text: str = "text") -> DataFrame:
    """Distinct (pattern, inst) of the tokens without digits in the slots of ``wanted``."""
    known = docs.sparkSession.sparkContext.broadcast((frozenset(wanted), frozenset(wanted.values())))

    def run(batches):
        keys, words = known.value
        for _, texts in _texts(batches, "text", every=True):
            pattern, inst = [], []
            for t in texts:
                if t is None:
                    continue
                good, bad = base_spans(t)
                for s, e, slots in slot_instances(t, Taken([(x, y) for x, y, _ in good] + bad), words):
                    for key in keys.intersection(slots):
                        pattern.append(key)
                        inst.append(_inst(t[s:e]))
            yield pa.RecordBatch.from_arrays([pa.array(pattern, pa.int64()), pa.array(inst, pa.int64())], ["pattern", "inst"])

    return counted(
        docs.select(F.col(text).alias("text")).mapInArrow(run, "pattern bigint, inst bigint").distinct(), "slot-edges"
    )[0]


@dataclass
class Patterns:
    """Confident patterns and slots: hash to (kind, confidence); the words before the slots."""

    kinds: dict[int, tuple[str, float]]
    words: frozenset[str] = frozenset()

    def judge(self, keys: list[int], least: float) -> str | None:
        doubt: dict[str, float] = {}
        for key in keys:
            if key in self.kinds:
                kind, sure = self.kinds[key]
                doubt[kind] = doubt.get(kind, 1.0) * (1 - sure)
        best = min(doubt.items(), key=lambda kv: (kv[1], kv[0]), default=None)
        return best[0] if best and 1 - best[1] >= least else None


def _scored(edges: DataFrame, known: DataFrame, support: int, confident: float) -> DataFrame:
    """(pattern, kind, hits, sure) of the patterns that mostly hold known entities of one kind."""
    sizes = edges.groupBy("pattern").agg(F.count("*").alias("size"))
    return (
        edges.join(known, "inst")
        .groupBy("pattern", "kind")
        .agg(F.count("*").alias("hits"))
        .filter(F.col("hits") >= support)
        .join(sizes, "pattern")
        .select("pattern", "kind", "hits", (F.col("hits") / (F.col("size") + 0.2)).alias("sure"))
        .filter(F.col("sure") >= confident)
    )


def _joining(edges: DataFrame, sure: DataFrame, accepted: float) -> DataFrame:
    """(inst, kind) of the instances whose patterns, taken together, leave little doubt."""
    return (
        edges.join(sure, "pattern")
        .groupBy("inst", "kind")
        .agg((1 - F.exp(F.sum(F.log(1 - F.col("sure"))))).alias("score"))
        .filter(F.col("score") >= accepted)
        .select("inst", "kind")
    )


def fit(docs: DataFrame, text: str = "text", support: int = 5, confident: float = 0.8, accepted: float = 0.9) -> Patterns:
    """Score patterns and instances by turns until no instance joins.

    Only confident patterns are gathered; each stands for at least ``support`` different entities.
    """
    edges, slots, known = pattern_graph(docs, text)
    in_slots = slots.select("pattern", "inst").distinct()
    wanted: dict[int, str] = {}
    letters = None
    while True:
        sure, _ = counted(_scored(edges, known, support, confident), "patterns")
        # a slot's confidence on tokens with digits bounds what it has with all tokens
        likely = _scored(in_slots, known, support, confident).select("pattern").distinct().join(slots, "pattern")
        fresh = [r for r in likely.groupBy("pattern").agg(F.min("before").alias("before")).collect() if r["pattern"] not in wanted]
        if fresh:
            new = {r["pattern"]: r["before"] for r in fresh}
            more = slot_graph(docs, new, text)
            wanted |= new
            letters = more if letters is None else letters.unionByName(more)
        joining = _joining(edges, sure, accepted)
        if letters is not None:
            sure_slots, _ = counted(
                _scored(in_slots.unionByName(letters), known, support, confident).join(
                    letters.select("pattern").distinct(), "pattern", "left_semi"
                ),
                "slots",
            )
            joining = joining.unionByName(_joining(letters, sure_slots, accepted))
        joined, n = counted(joining.distinct().join(known, ["inst", "kind"], "left_anti"), "joined")
        if not n:
            break
        known, _ = counted(known.unionByName(joined), "known")
    kinds: dict[int, tuple[str, float]] = {}
    words = set()
    for r in sure.orderBy("pattern", F.desc("sure"), "kind").collect():
        kinds.setdefault(r["pattern"], (r["kind"], float(r["sure"])))
    for r in sure_slots.orderBy("pattern", F.desc("sure"), "kind").collect() if letters is not None else []:
        kinds.setdefault(r["pattern"], (r["kind"], float(r["sure"])))
        words.add(wanted[r["pattern"]])
    return Patterns(kinds, frozenset(words))


def find_identifiers(
    docs: DataFrame,
    model: Patterns,
    text: str = "text",
    accepted: float = 0.9,
    redacted: bool = False,
) -> DataFrame:
    """All columns of ``docs`` plus base_spans and spans: arrays of (kind, start, end), ordered.

    Spans are code points, end exclusive. ``redacted=True`` also replaces each span of the text
    by its kind in angle brackets (overlapping spans as one).
    """
    known = docs.sparkSession.sparkContext.broadcast(model)
    names = [c for c in docs.columns if c not in ("base_spans", "spans")]
    span = pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())])
    order = {k: i for i, k in enumerate(KINDS)}

    def run(batches):
        patterns = known.value
        for batch, texts in _texts(batches, text, every=bool(patterns.words)):
            base, every, clean = [], [], []
            for t in texts:
                if t is None:
                    base.append([])
                    every.append([])
                    clean.append(None)
                    continue
                good, bad = base_spans(t)
                own = [(KINDS[k], s, e) for s, e, k in good]
                places = [(s, e, keys) for s, e, _, free, keys, _, _ in instances(t, good, bad) if free] if DIGIT.search(t) else []
                if patterns.words:
                    places += slot_instances(t, Taken([(s, e) for s, e, _ in good] + bad), patterns.words)
                more = []
                for s, e, keys in places:
                    kind = patterns.judge(keys, accepted)
                    if kind:
                        more.append((kind if kind == ADDED else f"like_{kind}", s, e))
                both = sorted(own + more, key=lambda x: (x[1], order.get(x[0], len(KINDS)), x[0], x[2]))
                base.append([dict(zip(("kind", "start", "end"), x, strict=True)) for x in own])
                every.append([dict(zip(("kind", "start", "end"), x, strict=True)) for x in both])
                clean.append(masked(t, both) if redacted and both else None)
            cols = {n: batch.column(n) for n in names}
            if redacted:
                changed = pa.array([c is not None for c in clean])
                cols[text] = pc.if_else(changed, pa.array(clean, cols[text].type), cols[text])
            yield pa.RecordBatch.from_arrays(
                [*cols.values(), pa.array(base, pa.list_(span)), pa.array(every, pa.list_(span))],
                [*names, "base_spans", "spans"],
            )

    rows = docs.select(*names)
    spans = "array<struct<kind:string,start:bigint,end:bigint>>"
    fields = ", ".join(f"`{n}` {t}" for n, t in rows.dtypes)
    return rows.mapInArrow(run, f"{fields}, base_spans {spans}, spans {spans}")


def masked(text: str, spans: list[tuple[str, int, int]]) -> str:
    out, at = [], 0
    for kind, start, end in spans:
        if end <= at:
            continue
        if start >= at:
            out += [text[at:start], f"<{kind}>"]
        at = max(at, end)
    return "".join([*out, text[at:]])


def query(spark, sf_dir: str) -> DataFrame:
    from bucketseed.tables import load

    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    found = find_identifiers(docs, fit(docs))
    listed = lambda c: F.array_join(
        F.transform(c, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ","
    )
    of_kind = lambda k: F.filter("base_spans", lambda s: s["kind"] == k)
    return found.select(
        "doc_id",
        *[F.size(of_kind(k)).cast("bigint").alias(f"n_{k}") for k in KINDS],
        F.sha2(listed("base_spans"), 256).alias("base_sha256"),
        listed("spans").alias("spans"),
    )
