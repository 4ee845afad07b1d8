"""Personal data by weak supervision.

Fixed patterns give base spans, which always stay. Wider patterns give candidates; regex, gazetteer and context labelers
vote on every candidate; expectation-maximisation over the counts of all vote patterns estimates how far each labeler
can be trusted; a final classifier over votes and shape is trained on the estimated labels and decides which candidates
join the base spans. Counts of patterns stand for all candidates of all documents, so nothing else goes to the driver.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import annotate, free, ship, staged, texts

#: The first four have base patterns; secrets (access tokens, keys) are only ever candidates.
KINDS = ("email", "ip", "card", "phone", "secret")

# Fixed patterns of the base.
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
HOST = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"(?<![0-9])[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")  # no match starts inside a run of digits
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")

# Wider patterns, for candidates that the base leaves out.
DIGIT = re.compile(r"[0-9]")
_NAME, _HOST, _LABEL = r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}", r"[A-Za-z0-9-]{1,63}", r"[A-Za-z0-9-]{2,24}"
SPELT_EMAIL = re.compile(
    rf"{_NAME} ?[(\[{{]at[)\]}}] ?{_HOST}(?: ?(?:[(\[{{]dot[)\]}}]|\.) ?{_LABEL}| dot {_LABEL}){{1,4}}|{_NAME} at {_HOST}(?: dot {_LABEL}){{1,4}}", re.I
)
LOCAL_PHONE = re.compile(r"(?<![0-9+.-])(?:\([0-9]{3}\)|[0-9]{3})[ .-][0-9]{3}[ .-][0-9]{4}(?![0-9])")
IP6 = re.compile(r"(?<![0-9A-Fa-f:])(?:[0-9A-Fa-f]{1,4}:){7}[0-9A-Fa-f]{1,4}(?![0-9A-Fa-f:])")
#: A long unbroken value; digits and letters must both be in it.
SECRET = re.compile(r"(?<![A-Za-z0-9_/+.@-])(?:[A-Za-z]{2,10}[_-])?[A-Za-z0-9_-]{20,200}(?![A-Za-z0-9_/+@-])")
HEXES = re.compile(r"[0-9a-f]+|[0-9A-F]+")

# Gazetteers and context words.
ENDINGS = frozenset("com org net edu gov mil int info biz io ai co uk de fr es it nl eu ch at be pl ru cn jp in br us ca au se no fi dk pt cz ie".split())
ISSUERS = ("4", "51", "52", "53", "54", "55", "34", "37", "6011", "65", "35", "30", "36", "38", "2221", "2720")
CUES = {
    "email": frozenset("email e-mail mail contact write reach address correo courriel adresse".split()),
    "ip": frozenset("ip address host server from login client adresse dirección".split()),
    "card": frozenset("card visa mastercard amex credit debit payment pan karte carte tarjeta".split()),
    "phone": frozenset("phone tel telephone call fax mobile cell ring telefon téléphone teléfono".split()),
    "secret": frozenset("token key apikey api_key api-key secret password passwd pwd auth authorization bearer credential credentials access_token".split()),
}
#: How keys of well-known services begin.
ISSUED = ("AKIA", "ASIA", "ghp_", "gho_", "ghs_", "github_pat_", "glpat-", "sk-", "sk_live_", "pk_live_", "rk_live_", "xoxb-", "xoxp-", "AIza", "eyJ")
COUNTER = frozenset("version v release section chapter isbn issn order invoice ticket id serial hash commit build part no number figure".split())
NEAR = re.compile(r"[^\W\d_][\w-]*")


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = int(c) * (2 if k % 2 else 1)
        total += d - 9 if d > 9 else d
    return total % 10 == 0


def digits_of(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def emails(text: str) -> list[tuple[int, int]]:
    """Leftmost, non-overlapping matches; linear, for each at-sign is asked once how far the name before it reaches."""
    out, end, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > end and text[start - 1] in LOCAL:
            start -= 1
        m = HOST.match(text, at + 1) if start < at else None
        if m:
            out.append((start, m.end()))
            end = m.end()
        at = text.find("@", max(at + 1, end))
    return out


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind index, end), in order."""
    out = [(a, 0, b) for a, b in emails(text)] if "@" in text else []
    if DIGIT.search(text):
        out += [(m.start(), 1, m.end()) for m in IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p) <= 255 for p in m.group().split("."))]
        for m in CARD.finditer(text):
            d = digits_of(m.group())
            if 12 <= len(d) <= 19 and luhn(d):
                out.append((m.start(), 2, m.end()))
        if "+" in text:
            out += [(m.start(), 3, m.end()) for m in PHONE.finditer(text) if 9 <= len(digits_of(m.group())) <= 15]
    return sorted(out)


def candidates(text: str, base: list[tuple[int, int, int]]) -> list[tuple[int, int, int, str]]:
    """(start, kind, end, code) of every base span and wider match; the code holds votes and shape, nothing of the text."""
    found = [(s, k, e, True) for s, k, e in base]
    lower = text.lower() if "at" in text or "AT" in text else ""
    if any(x in lower for x in ("(at)", "[at]", "{at}")) or (" at " in lower and " dot " in lower):
        found += [(m.start(), 0, m.end(), False) for m in SPELT_EMAIL.finditer(text)]
    if DIGIT.search(text):
        found += [(m.start(), 3, m.end(), False) for m in LOCAL_PHONE.finditer(text)]
        found += [(m.start(), 2, m.end(), False) for m in CARD.finditer(text) if 12 <= len(digits_of(m.group())) <= 19 and not luhn(digits_of(m.group()))]
        if ":" in text:
            found += [(m.start(), 1, m.end(), False) for m in IP6.finditer(text)]
        if len(text) >= 20:
            found += [(m.start(), 4, m.end(), False) for m in SECRET.finditer(text) if DIGIT.search(m.group()) and re.search(r"[A-Za-z]", m.group()) and len(set(m.group())) >= 10]
    taken = {(s, e) for s, _, e in base}
    out = []
    for s, k, e, is_base in found:
        if is_base or not any(a < e and s < b for a, b in taken):
            out.append((s, k, e, code(text, s, k, e, is_base)))
    return out


def code(text: str, start: int, kind: int, end: int, is_base: bool) -> str:
    """``kind|regex,gazetteer,context,edges|shape``; votes are 1 for, 0 against, - for none."""
    span, before, after = text[start:end], text[max(0, start - 48) : start], text[end : end + 1]
    digits = digits_of(span)
    if kind == 0:
        strict = "1" if is_base else ("1" if re.search(r"[(\[{](?:at|dot)[)\]}]", span, re.I) else "-" if re.search(r" dot ", span, re.I) else "0")
        listed = "1" if re.split(r"[.\s)\]}]+", span.rstrip(")]} ").lower())[-1] in ENDINGS else "0"
    elif kind == 1:
        strict = "1"
        parts = span.split(".")
        listed = ("0" if parts[0] in ("0", "127", "255") else "1") if len(parts) == 4 else "-"
    elif kind == 2:
        strict = "1" if is_base else "0"
        listed = "1" if digits.startswith(ISSUERS) else "0"
    elif kind == 4:
        even = HEXES.fullmatch(span) and len(span) in (32, 40, 48, 56, 64, 96, 128)
        strict = "1" if even or (span.lower() != span and span.upper() != span and len(digits) > 2) else "0"
        listed = "1" if span.startswith(ISSUED) else "-"
    else:
        strict = "1" if is_base or "(" in span else "-"
        listed = "1" if is_base else ("0" if digits[0] in "01" else "-")
    words = [w.lower() for w in NEAR.findall(before)][-4:]
    context = "1" if CUES[KINDS[kind]].intersection(words) else "0" if COUNTER.intersection(words) else "-"
    edge = "0" if before[-1:].isalnum() or after.isalnum() else "1"
    if kind == 4:  # given as a value: quoted, or after an equals sign or a colon
        edge = "1" if before.rstrip(" \t\"'`")[-1:] in ("=", ":") or before[-1:] in ("'", '"', "`") else "0"
    shape = f"{min(len(span) // 8, 5)}{min(len(digits) // 4, 5)}{int(is_base)}"
    return f"{kind}|{strict}{listed}{context}{edge}|{shape}"


class SpanModel:
    """Reliabilities by expectation-maximisation for each kind, then logistic regression over all codes."""

    def __init__(self, counts: dict[str, int]):
        self.counts = counts
        self.reliability: dict[int, np.ndarray] = {}
        self.chance: dict[str, float] = {}
        if counts:
            self._fit()

    def _estimate(self, kind: int) -> dict[str, float]:
        """Chance of being personal data for every vote pattern; ``reliability[kind]`` holds P(vote | class)."""
        seen: dict[str, int] = {}
        for c, n in self.counts.items():
            k, votes, _ = c.split("|")
            if int(k) == kind:
                seen[votes] = seen.get(votes, 0) + n
        if not seen:
            return {}
        patterns, n = list(seen), np.array(list(seen.values()), float)
        votes = np.array([[{"0": 0, "1": 1, "-": -1}[v] for v in p] for p in patterns])
        for_, against = (votes == 1).sum(axis=1), (votes == 0).sum(axis=1)
        q = np.clip((for_ + 1) / (for_ + against + 2), 0.1, 0.9)  # majority starts it
        rate = np.full((votes.shape[1], 2), 0.7)  # chance that a vote is right, of a true and of a false candidate
        for _ in range(100):
            prior = (n @ q + 1) / (n.sum() + 2)
            for j in range(votes.shape[1]):
                own = votes[:, j] >= 0
                w, v = n[own], votes[own, j]
                rate[j, 0] = (w @ (q[own] * (v == 1)) + 4) / (w @ q[own] + 5)
                rate[j, 1] = (w @ ((1 - q[own]) * (v == 0)) + 4) / (w @ (1 - q[own]) + 5)
            rate = np.clip(rate, 0.55, 0.99)  # a labeler is better than chance
            yes, no = np.log(prior), np.log(1 - prior)
            a = yes + ((votes == 1) * np.log(rate[:, 0]) + (votes == 0) * np.log(1 - rate[:, 0])).sum(axis=1)
            b = no + ((votes == 0) * np.log(rate[:, 1]) + (votes == 1) * np.log(1 - rate[:, 1])).sum(axis=1)
            new = 1 / (1 + np.exp(np.clip(b - a, -50, 50)))
            if np.abs(new - q).max() < 1e-9:
                break
            q = new
        self.reliability[kind] = rate
        return dict(zip(patterns, q.tolist(), strict=True))

    @staticmethod
    def row(c: str) -> np.ndarray:
        kind, votes, shape = c.split("|")
        k = len(KINDS)
        x = np.zeros(1 + k + 12 + 12)
        x[0] = 1
        x[1 + int(kind)] = 1
        for j, v in enumerate(votes):
            x[1 + k + 3 * j + "01-".index(v)] = 1
        x[13 + k + int(shape[0])] = 1
        x[19 + k + int(shape[1])] = 1
        return x

    def _fit(self) -> None:
        labels = {k: self._estimate(k) for k in range(len(KINDS))}
        codes = sorted(self.counts)
        x = np.array([self.row(c) for c in codes])
        y = np.array([labels[int(c[0])][c.split("|")[1]] for c in codes])
        n = np.sqrt(np.array([self.counts[c] for c in codes], float))  # a common pattern must not drown the others
        w = np.zeros(x.shape[1])
        for _ in range(60):  # Newton steps
            p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
            grad = x.T @ (n * (p - y)) + 0.1 * w
            hess = (x * (n * p * (1 - p))[:, None]).T @ x + 0.1 * np.eye(len(w))
            step = np.linalg.solve(hess, grad)
            w -= step
            if np.abs(step).max() < 1e-9:
                break
        self.chance = dict(zip(codes, (1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))).tolist(), strict=True))


SPAN = T.StructType([T.StructField("start", T.LongType()), T.StructField("kind", T.IntegerType()), T.StructField("end", T.LongType()), T.StructField("code", T.StringType()), T.StructField("base", T.BooleanType())])


def detect(docs: DataFrame, text_col: str = "text", out: str = "pii", keep: list[str] | None = None, threshold: float = 0.5) -> DataFrame:
    """``docs`` with all spans found: array of (start, kind, end, base), by start, then kind; code points, end exclusive.

    Texts are read once: spans and codes go to a staged table, the codes are counted over all of it, and the model made
    from the counts (a few hundred at most, for a code has few values) decides there. A candidate that fails its format
    (a card its checksum) never joins, whatever else votes for it. Null and empty texts have no spans.
    """
    ship(docs.sparkSession)
    held_in = free(docs, "_found")

    def start():
        def work(batch: pa.RecordBatch) -> dict[str, list]:
            made = []
            for t in texts(batch, text_col):
                base = base_spans(t)
                own = set(base)
                made.append([{"start": s, "kind": k, "end": e, "code": c, "base": (s, k, e) in own} for s, k, e, c in sorted(candidates(t, base))])
            return {held_in: made}

        return work

    found = staged(annotate(docs, start, [T.StructField(held_in, T.ArrayType(SPAN))], [text_col], keep), "pii")
    counts = found.select(F.explode(F.col(held_in)["code"]).alias("code")).groupBy("code").agg(F.count("*").alias("n")).collect()
    model = SpanModel({r.code: r.n for r in counts})
    good = [c for c, p in sorted(model.chance.items()) if p > threshold and c[2] != "0"]  # a failed format is a veto
    held = F.filter(held_in, lambda s: s["base"] | s["code"].isin(good))
    spans = F.transform(held, lambda s: F.struct(s["start"].alias("start"), s["kind"].alias("kind"), s["end"].alias("end"), s["base"].alias("base")))
    return found.withColumn(out, spans).drop(held_in)


def redact(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``docs`` with every span replaced by its kind in brackets; overlapping spans by that of the first. Null stays null."""
    pii, new = free(docs, "_pii"), free(docs, "_text")
    found = detect(docs, text_col, pii)
    names = [k.upper() for k in KINDS]

    def start():
        def work(batch: pa.RecordBatch) -> dict[str, list]:
            out = []
            spans = batch.column(batch.schema.get_field_index(pii)).to_pylist()
            for t, own in zip(batch.column(batch.schema.get_field_index(text_col)).to_pylist(), spans, strict=True):
                if not own:
                    out.append(t)
                    continue
                parts, at = [], 0
                for s in own:
                    if s["start"] >= at:
                        parts += [t[at : s["start"]], f"[{names[s['kind']]}]"]
                    at = max(at, s["end"])
                out.append("".join([*parts, t[at:]]))
            return {new: out}

        return work

    done = annotate(found, start, [T.StructField(new, T.StringType())], [text_col, pii], docs.columns)
    return done.select(*(F.col(new).alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns))


def listing(spans, base_only: bool):
    kind = F.array(*map(F.lit, KINDS))
    own = F.filter(spans, lambda s: s["base"]) if base_only else spans
    return F.array_join(F.transform(own, lambda s: F.concat_ws(":", F.element_at(kind, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")


def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = detect(spark.read.parquet(f"{sf_dir}/documents.parquet"), keep=["doc_id"])
    count = lambda k: F.size(F.filter("pii", lambda s: s["base"] & (s["kind"] == k))).cast("long")
    return found.select(
        "doc_id", *(count(i).alias(f"n_{k}") for i, k in enumerate(KINDS[:4])),
        F.sha2(listing(F.col("pii"), True), 256).alias("base_sha256"), listing(F.col("pii"), False).alias("spans"),
    )
