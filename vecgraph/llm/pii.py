"""Personal data: fixed patterns for e-mail addresses, IPv4 addresses, payment cards and telephone numbers, and spans that a
conditional random field over word shapes adds to them (disguised and spelt-out addresses, IPv6, other separators, national number
formats) together with a kind of its own, secrets (keys, tokens and passwords).

The model is trained on a small labelled table of (line, spans); a table made from templates is built in. A sequence is one line of the text, whatever its
length, and the whole text is decoded line by line; a line without a digit, an at-sign or a spelt-out at or dot is passed over,
since every added span must hold one of them. An added span never overlaps a pattern's span and must
pass the check of its kind (Luhn for cards, parts up to 255 for addresses, 10 to 15 digits with separators for telephone numbers, a run of 16 letters and digits for secrets).

Offsets are code points of the whole text, ends exclusive. Null texts count as empty and have no spans; rows repeated whole are each
reported; other columns of the input pass through, those named like a result are replaced. An empty table gives an empty result."""

from __future__ import annotations

import hashlib
import ipaddress
import random
import re

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import prepare, shared_dir, table
from .crf import Line, ShapeCRF

KINDS = ["email", "ip", "card", "phone"]
ALL_KINDS = [*KINDS, "secret"]
# The patterns of the contract. What a look-behind or possessive quantifier adds only spares failing starts.
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL = re.compile(r"[A-Za-z0-9._%+-]+\Z")
_IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_LOCAL_SIGNS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
# One of these is in every span that the model may add.
MAYBE = r"(?i)[0-9@]|[\[({<]\s?at\s?[\])}>]|\sat\s|AKIA"
_MAYBE = re.compile(MAYBE)


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        x = int(d) * (1 + i % 2)
        total += x - 9 * (x > 9)
    return total % 10 == 0


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """Spans of the fixed patterns by kind, then start."""
    out, floor, at = [], 0, text.find("@")
    while at >= 0:
        a = at
        while a > floor and text[a - 1] in _LOCAL_SIGNS:
            a -= 1
        m = _DOMAIN.match(text, at + 1) if a < at else None
        if m:
            out.append(("email", a, m.end()))
            floor = m.end()
        else:
            floor = max(floor, at + 1)
        at = text.find("@", max(at + 1, floor))
    out += [("ip", *m.span()) for m in _IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or "0") <= 255 for p in m[0].split("."))]
    for m in _CARD.finditer(text):
        if m.end() - m.start() <= 40:
            digits = re.sub("[ -]", "", m[0])
            if 16 <= len(digits) <= 19 and luhn(digits):
                out.append(("card", *m.span()))
    for m in _PHONE.finditer(text):
        if 8 <= sum(map(m[0].count, "0123456789")) <= 15:
            out.append(("phone", *m.span()))
    return out


def example_rows(n: int = 1000, seed: int = 11) -> list[tuple[str, list[tuple[str, int, int]]]]:
    """The built-in labelled table, made from templates: (line, [(kind, start, end)])."""
    r = random.Random(seed)
    pick = r.choice
    letters = lambda signs, k: "".join(pick(signs) for _ in range(k))
    word = lambda: "".join(pick(["an", "ther", "on", "st", "que", "la", "ch", "ei", "ér", "ción", "do", "en"]) for _ in range(r.randint(1, 4)))
    plain_word = lambda: "".join(pick(["an", "ther", "on", "st", "que", "la", "ch", "ei", "do", "en"]) for _ in range(r.randint(1, 4)))
    text = lambda k: " ".join(w.capitalize() + pick(["", ".", ",", ";", ":"]) if r.random() < 0.2 else w for w in (word() for _ in range(k)))
    digits = lambda k: letters("0123456789", k)
    user = lambda: plain_word() + pick(["", "", "." + digits(2), "_" + plain_word(), "." + plain_word(), "-" + plain_word(), digits(2)])
    top = ["com", "org", "net", "de", "fr", "es", "io", "info"]
    host = lambda d=".": d.join([*([pick(["mail", "mail" + digits(1), plain_word()])] if r.random() < 0.5 else []), pick(["example", plain_word()]), pick(top)])

    def card(sep: str) -> str:
        body = pick("3456") + digits(14)
        body += next(c for c in "0123456789" if luhn(body + c))
        return sep.join(body[i : i + 4] for i in range(0, 16, 4))

    def hidden_mail() -> str:
        at, dot = pick([(" [at] ", " [dot] "), (" (at) ", " (dot) "), ("[at]", "[dot]"), ("(at)", "(dot)"), (" {at} ", " {dot} "), (" <at> ", " <dot> "), (" at ", " dot "), (" AT ", " DOT "), (" @ ", " . "), (" @ ", "."), ("(at)", "."), (" [at] ", "."), ("@", " dot "), (" (at) ", " dot ")])
        return user() + at + host(dot)

    def address() -> str:
        if r.random() < 0.2:
            return str(ipaddress.IPv6Address(r.getrandbits(128) if r.random() < 0.5 else 0x20010DB8 << 96 | r.getrandbits(20)))
        return pick([".", ".", "[.]", "(.)", "[dot]", " . ", " dot ", " [.] "]).join(str(r.randint(0, pick([9, 99, 255, 255]))) for _ in range(4))

    def phone() -> str:
        return pick([f"+1 ({digits(3)}) {digits(3)}-{digits(4)}", f"({digits(3)}) {digits(3)}-{digits(4)}", f"{digits(3)}-{digits(3)}-{digits(4)}", f"{digits(3)}.{digits(3)}.{digits(4)}", f"00{digits(2)} {digits(3)} {digits(3)} {digits(4)}", f"+{digits(2)} {digits(3)} {digits(7)}", f"0{digits(1)} {digits(2)} {digits(2)} {digits(2)} {digits(2)}", f"0{digits(1)}.{digits(2)}.{digits(2)}.{digits(2)}.{digits(2)}", f"0{digits(2)} {digits(4)} {digits(4)}", f"0{digits(3)}/{digits(7)}", f"0{digits(3)} {digits(3)} {digits(3)}"])

    def secret() -> tuple[str, str, str]:
        value = pick([lambda: letters("0123456789abcdef", pick([18, 32, 40, 64])), lambda: "AKIA" + letters("ABCDEFGHIJKLMNOPQRSTUVWXYZ234567", 16), lambda: pick(["sk-", "ghp_", "xoxb-", ""]) + letters("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789", 36)])()
        name = pick(["password", "passwd", "pwd", "token", "secret", "api_key", "apikey", "key", "auth", "access_token", "client_secret"])
        shown = pick([f"{name}=", f'{name} = "', f"{name}: ", f"{name} = '", f'"{name}": "', "Authorization: Bearer ", "bearer ", "key ", ""])
        if not shown and not value.startswith(("AKIA", "sk-", "ghp_", "xoxb-")):
            shown = f"{name}="
        return shown, value, {'"': '"', "'": "'"}.get(shown[-1:], "")

    make = {"email": lambda: user() + "@" + host() if r.random() < 0.3 else hidden_mail(), "ip": address, "card": lambda: card(pick(["", " ", "-", ".", "  ", "/", "_", " - "])), "phone": phone}
    before = {"email": ["", "", "mail ", "email: ", "mail: "], "ip": ["", "", "ip ", "host ", "address: "], "card": ["", "", "card ", "visa "], "phone": ["", "", "tel ", "phone: ", "call ", "fax ", "mobile "]}
    hexes = lambda k: letters("0123456789abcdef", k)
    plain = [lambda: f"version {r.randint(1, 9)}.{r.randint(0, 9)}", lambda: f"version {r.randint(1, 9)}.{r.randint(0, 9)}.{r.randint(0, 20)}", lambda: f"version {r.randint(1, 9)}.{r.randint(0, 9)}.{r.randint(0, 20)}.{digits(4)}", lambda: f"{r.randint(1990, 2030)}-{r.randint(10, 12)}-{r.randint(10, 28)}", lambda: f"{r.randint(1, 12)}/{r.randint(1, 28)}/{r.randint(1990, 2030)}", lambda: f"{digits(2)}:{digits(2)}", lambda: f"{digits(2)}:{digits(2)}:{digits(2)}", lambda: f"page {r.randint(1, 999)}", lambda: f"order {digits(6)}", lambda: digits(pick([1, 2, 3, 4, 5, 6, 8, 12, 16, 20])), lambda: f"{digits(1)},{digits(3)}.{digits(2)}", lambda: f"{pick(['commit', 'sha1', 'revision', 'digest'])} {hexes(40)}", lambda: f"{pick(['sha256', 'checksum', 'digest'])}: {hexes(64)}", lambda: f"md5 {hexes(32)}", lambda: f"{hexes(8)}-{hexes(4)}-{hexes(4)}-{hexes(4)}-{hexes(12)}", lambda: f"CC BY-NC {r.randint(1, 4)}.0", lambda: f"{word()} at {word()}", lambda: f"{word()} at {word()} dot", lambda: f"{word()} dot {word()}", lambda: f"@{word()}", lambda: f"{digits(1)} - {digits(1)}", lambda: f"{digits(3)} {digits(4)} {word()}", lambda: f"{digits(4)} {digits(4)}", lambda: f"{digits(1)} {digits(2)} {digits(1)} {digits(3)}", lambda: f"### {digits(16)}$$$ {word()},&&& {word()}%%", lambda: f"token {word()}", lambda: f"the key {word()}", lambda: f"password: {word()}", lambda: f"arXiv:{digits(4)}.{digits(5)}", lambda: f"{letters('abcdefghijklmnopqrstuvwxyz', 14)}{digits(2)}"]
    rows = []
    for _ in range(n):
        parts: list[tuple[str | None, str]] = []
        for _ in range(r.randint(1, 3)):
            if r.random() < 0.85:
                parts.append((None, text(r.randint(1, 7)) + " "))
            kind = pick([*KINDS, "secret", None, None, None])
            if kind == "secret":
                shown, value, closing = secret()
                parts += [(None, shown), (kind, value), (None, closing + pick([" ", " ", ", ", ".", "### "]))]
            elif kind:
                parts += [(None, pick(before[kind])), (kind, make[kind]()), (None, pick([" ", " ", ", ", ". ", "; ", "### "]))]
            else:
                parts.append((None, pick(plain)() + " "))
        parts.append((None, text(r.randint(0, 5))))
        out, spans = "", []
        for kind, part in parts:
            if kind:
                spans.append((kind, len(out), len(out) + len(part)))
            out += part
        rows.append((out, spans))
    return rows


def train(rows: list[tuple[str, list[tuple[str, int, int]]]] | None = None) -> ShapeCRF:
    return ShapeCRF(ALL_KINDS).fit(example_rows() if rows is None else rows)


def model_of(spark: SparkSession, rows: list[tuple[str, list[tuple[str, int, int]]]] | None = None) -> ShapeCRF:
    """The model of a labelled table. Its weights are a table in the shared folder, named by a hash of the labels; training happens only where that is missing."""
    rows = example_rows() if rows is None else rows
    path = f"{shared_dir(spark)}/pii-crf-{hashlib.sha256(repr((ALL_KINDS, rows)).encode()).hexdigest()[:32]}"
    schema = "kinds array<string>, shapes array<string>, keys binary, emit binary, move binary"
    try:
        there = spark.read.schema(schema).parquet(path).collect()
    except AnalysisException:  # no such path
        there = []
    if there:
        return ShapeCRF.restored(there[0].asDict())
    model = train(rows)
    spark.createDataFrame([model.stored()], schema).coalesce(1).write.mode("overwrite").parquet(path)
    return model


def plausible(kind: str, span: str) -> bool:
    digits = re.sub(r"\D", "", span) if span.isascii() else ""
    if kind == "email":
        return bool(re.fullmatch(r"[A-Za-z0-9._%+-]+\s?(?:@|[\[({<]\s?at\s?[\])}>]|(?<=\s)at(?=\s))\s?[A-Za-z0-9-]+(?:\s?(?:\.|[\[({<]\s?dot\s?[\])}>]|(?<=\s)dot(?=\s))\s?[A-Za-z0-9-]+)+", span, re.I))
    if kind == "ip":
        if span.count(":") >= 2:
            try:
                return ipaddress.IPv6Address(span) is not None and len(digits) > 1
            except ValueError:
                return False
        parts = re.split(r"\s?[\[(]?\s?(?:\.|dot)\s?[\])]?\s?", span, flags=re.I)
        return len(parts) == 4 and all(re.fullmatch(r"[0-9]{1,3}", p) and int(p) <= 255 for p in parts)
    if kind == "card":
        return 16 <= len(digits) <= 19 and bool(re.fullmatch(r"[0-9]+(?:[ ./_-]{1,3}[0-9]+){3,4}", span)) and luhn(digits)
    if kind == "secret":
        return span.isascii() and any(x.startswith("AKIA") or sum(map(str.isdigit, x)) >= 2 and not x.isdigit() for x in re.findall("[A-Za-z0-9]{16,}", span)) and not re.search(r"\s", span)
    national = r"(?:00[0-9]{1,3}[ .-]?)?\(?[0-9]{2,4}\)?(?:[ .-][0-9]{2,4}){2,3}"
    if digits.startswith("0") and re.fullmatch(r"0[0-9](?:[ .-][0-9]{2}){4}|0[0-9]{1,4}[ ./-][0-9]{3,4}[ ]?[0-9]{3,5}", span):
        return 10 <= len(digits) <= 15
    return 10 <= len(digits) <= 15 and bool(re.fullmatch(national, span)) and (digits.startswith("00") or len(digits) == 10)


def lines_of(text: str) -> list[tuple[int, str]]:
    """Start and text of the lines that may hold a span to add."""
    out, at = [], 0
    for line in text.split("\n"):
        if _MAYBE.search(line):
            out.append((at, line))
        at += len(line) + 1
    return out


def find(texts: list[str | None], model: ShapeCRF, chars: int = 1 << 20) -> list[tuple[list[tuple[str, int, int]], list[tuple[str, int, int]]]]:
    """For each text the spans of the patterns and the spans that the model adds; lines are decoded `chars` characters at a time."""
    base = [base_spans(t) if t else [] for t in texts]
    added: list[list[tuple[str, int, int]]] = [[] for _ in texts]
    held: list[tuple[int, int, Line]] = []

    def settle() -> None:
        for (k, start, line), states in zip(held, model.decode([x[2] for x in held]), strict=True):
            for kind, s, e in model.spans(line.tokens, states):
                s, e = s + start, e + start
                if not any(s < y and x < e for _, x, y in base[k]) and plausible(kind, texts[k][s:e]):
                    added[k].append((kind, s, e))
        held.clear()

    size = 0
    for k, t in enumerate(texts):
        for start, line in lines_of(t) if t else []:
            held.append((k, start, Line(line, model)))
            size += len(line)
            if size >= chars:
                settle()
                size = 0
    settle()
    return list(zip(base, added, strict=True))


def detect(docs: DataFrame, text: str = "text", model: ShapeCRF | None = None) -> DataFrame:
    """docs with n_email, n_ip, n_card, n_phone (of the patterns), n_secret, n_added (by the model), n_spans (all), base and spans (arrays of kind, start, end; by kind, then start)."""
    prepare(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast(model or model_of(docs.sparkSession))
    span = "array<struct<kind string, start long, end long>>"

    @F.arrow_udf(f"struct<base {span}, spans {span}>")
    def spans(texts: pa.Array) -> pa.Array:
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))
        maybe = pc.fill_null(pc.match_substring_regex(texts, MAYBE), False).to_pylist()
        out = [([], [])] * len(texts)
        some = [i for i, x in enumerate(maybe) if x]
        key = lambda x: (ALL_KINDS.index(x[0]), x[1], x[2])
        for i, (base, added) in zip(some, find([texts[i].as_py() for i in some], sent.value), strict=True):
            out[i] = (sorted(base, key=key), sorted(base + added, key=key))
        named = lambda x: [dict(zip(("kind", "start", "end"), s, strict=True)) for s in x]
        return pa.StructArray.from_arrays([pa.array([named(x[i]) for x in out], kind) for i in (0, 1)], ["base", "spans"])

    out = docs.withColumn("_p", spans(F.col(text).cast("string")))
    of_kind = lambda k: F.size(F.filter("_p.base", lambda s: s["kind"] == k)).cast("long")
    out = out.withColumns({"base": F.col("_p.base"), "spans": F.col("_p.spans")} | {f"n_{k}": of_kind(k) for k in KINDS})
    secrets = F.size(F.filter("_p.spans", lambda s: s["kind"] == "secret")).cast("long")
    return out.withColumns({"n_secret": secrets, "n_added": (F.size("_p.spans") - F.size("_p.base")).cast("long"), "n_spans": F.size("_p.spans").cast("long")}).drop("_p")


def _joined(col: str) -> object:
    return F.array_join(F.transform(col, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def op1_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = detect(docs)
    return found.select("doc_id", *(f"n_{k}" for k in KINDS), F.sha2(_joined("base"), 256).alias("base_sha256"), _joined("spans").alias("spans"), "n_secret", "n_added", "n_spans")
