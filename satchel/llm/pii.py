"""Personal data: spans by weak supervision, with built-in SQL functions only.

Base spans (e-mail, ip, card, phone) follow fixed patterns and checks and always stay. Wider patterns propose
further spans of these kinds and of secrets (keys, tokens, passwords): spelled-out and spaced forms, base forms
that fail their check, IPv6, cards with other breaks, national phone numbers, versions, dates, times and long mixed
runs, so that there is something to turn down in every kind. Five labelers vote on every candidate, base or not: -1
against, 0 silent, 1 for. They are patterns (shape, check), gazetteers (domains, issuer digits, reserved networks, key
prefixes) and context (words before, what touches it).

Votes are counted over all documents, as at most KINDS * 3^5 patterns; expectation-maximisation over that table
estimates each labeler's reliability per kind. Its posteriors are the soft labels of the final span classifier, a
logistic model per kind over features of the span (length, digits, marks, what shape and check say, a hash of
the word before, what comes after), for which counts and sums of posteriors by feature pattern (FEATURE_PATTERNS a kind at most) suffice.
Candidates that the classifier accepts are added.

A pattern's matches and the gaps between them come from one split and one extraction, so positions need no
Python; running sums and choices go through chunks of CHUNK spans, so a text with many stays cheap. Patterns are
written possessively where that changes nothing, so long runs cost no backtracking and no stack. Expressions are
put together as SQL text: one call to the JVM for each, instead of one for each part.

Defined results: a null text is empty and has no spans; positions are code points, end exclusive; candidates
that overlap a base span or an earlier accepted one are dropped; repeated rows are each searched; an empty
table gives no rows; other columns are not read, and redact() returns them as they are.
"""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialize, table

KINDS = ("email", "ip", "card", "phone", "secret")
CHUNK = 256
_LOCAL, _LABEL = "A-Za-z0-9._%+-", "A-Za-z0-9-"
#: Per kind: the base pattern, and one without which no match can be.
BASE = {
    "email": (rf"(?:\G|(?<![{_LOCAL}]))[{_LOCAL}]++@[{_LABEL}]++(?:\.[{_LABEL}]++)++", "@"),
    "ip": (r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", "."),
    "card": (r"[0-9]++(?:[\x20-][0-9]++)*+", ""),
    "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", "+"),
}
_OCTET_GAP = r"(?:\[\.\]|\(\.\)|\[dot\]|\(dot\)|\x20\.\x20?|\x20dot\x20)"
_AT = r"(?:\x20?[(\[](?i:at)[)\]]\x20?|\x20@\x20?|@\x20)"
_DOT = r"(?:\x20?[(\[](?i:dot)[)\]]\x20?|\x20dot\x20|\.|\x20\.\x20?)"
#: Further candidates, with a pattern that the text must hold.
WIDER = {
    "email": (rf"(?<![{_LOCAL}])[{_LOCAL}]{{1,64}}+(?:{_AT}[{_LABEL}]{{1,63}}+(?:{_DOT}[{_LABEL}]{{1,63}}+){{1,8}}+|\x20at\x20[{_LABEL}]{{1,63}}+(?:\x20dot\x20[{_LABEL}]{{1,63}}+){{1,8}}+|@[{_LABEL}]{{1,63}}+(?![{_LABEL}]|\.[{_LABEL}]))", r"@|[(\[](?i:at)[)\]]|\x20dot\x20"),
    "ip": (rf"(?<![0-9A-Za-z:.])(?:[0-9A-Fa-f]{{0,4}}+(?::[0-9A-Fa-f]{{0,4}}+){{2,7}}+(?![0-9A-Za-z:])|[0-9]{{1,4}}+(?:{_OCTET_GAP}[0-9]{{1,4}}+){{3}}+(?![0-9])|[0-9]{{1,6}}+(?:\.[0-9]{{1,6}}+){{3,5}}+(?![0-9]))", r"[0-9](?::|\.[0-9]|[\[(]|\x20\.|\x20dot)|:[0-9A-Fa-f:]"),
    "card": (r"(?<![0-9])(?:[0-9]{13,19}+|[0-9]{3,6}+(?:[\x20./_-]{1,2}+[0-9]{2,7}+){2,5}+)(?![0-9])", "[0-9]{3}"),
    "phone": (r"(?<![0-9A-Za-z+.-])(?:(?:\+|00)[0-9]{1,3}[\x20.-]?)?(?:\(0?[0-9]{2,5}\)\x20?|[0-9]{2,5}[\x20./-])[0-9]{2,5}+(?:[\x20./-][0-9]{2,5}+){0,3}(?![0-9A-Za-z-]|\.[0-9])", "[0-9]{2}"),
    "secret": (r"-----BEGIN\x20[A-Z\x20]{0,30}PRIVATE\x20KEY-----[A-Za-z0-9+/=\s]{0,8192}+(?:-----END\x20[A-Z\x20]{0,30}PRIVATE\x20KEY-----)?|(?<![A-Za-z0-9+/_-])(?=[A-Za-z+/_-]{0,64}+[0-9])[A-Za-z0-9+/_-]{8,512}+={0,2}", "[0-9][A-Za-z+/_-]|[A-Za-z+/_-][0-9]|-----BEGIN"),
}
#: Fixed word lists of the gazetteer and context labelers.
DOMAINS = "com|org|net|edu|gov|mil|info|biz|io|co|app|dev|me|de|fr|es|uk|eu|us|ch|at|it|nl|be|pt|pl|se|ca|au|jp|cn|in|br|mx|ru"
NEAR = {"email": "e-?mail|mail|contact|correo|courriel|kontakt|write|from|to|cc", "ip": "ips?|host|server|addr|address|login|client|peer|route", "card": "card|visa|mastercard|credit|debit|carte|karte|tarjeta|payment|pan", "phone": "phone|tel|call|mobile|cell|fax|telefon|llame|appel|whatsapp|sms|ring", "secret": "pass(?:word|wd|phrase)?|pwd|secret|token|key|bearer|auth|credentials?|signature"}
AGAINST = "order|invoice|version|isbn|issn|doi|serial|build|release|section|figure|fig|page|pages|id|no|commit|sha|sha1|sha256|md5|hash|checksum|digest|uuid|date|on|at|time"
KEYS = "AKIA|ASIA|gh[pousr]_|github_pat_|glpat-|sk-|sk_live_|sk_test_|rk_live_|xox[abprs]-|AIza|ya29|eyJ|-----BEGIN"
DUMMIES = "example|sample|dummy|changeme|placeholder|xxxx|lorem|1234567"
LABELERS = ("shape", "check", "gazetteer", "context", "edges")
#: Features of a span and how many values each has.
FEATURES = {"f_length": 7, "f_digits": 5, "f_marks": 4, "f_form": 9, "f_before": 5, "f_after": 3}
FEATURE_PATTERNS = math.prod(FEATURES.values())
#: A span is accepted with this probability at least, and only if MARGIN more labelers are for it than against: where a
#: kind has no false candidates at all, nothing else would hold the classifier back.
ACCEPT, MARGIN = 0.9, 2
SPAN = "struct<start: bigint, kind: int, stop: bigint>"


def _raw(pattern: str) -> str:
    """A pattern as an SQL literal."""
    assert '"' not in pattern
    return f'r"{pattern}"'


def _like(value: str, pattern: str) -> str:
    return f"rlike({value}, {_raw(pattern)})"


def _digits(value: str) -> str:
    return f"regexp_replace({value}, {_raw('[^0-9]')}, '')"


def _luhn(value: str) -> str:
    return f"luhn_check({_digits(value)})"


def base_check(kind: str, value: str) -> str:
    if kind == "ip":
        return _like(value, r"^(?:0*+(?:(?<=0)|25[0-5]|2[0-4][0-9]|1[0-9]{2}|[1-9][0-9]?)(?:\.|$)){4}")
    if kind == "card":
        return f"(length({_digits(value)}) BETWEEN 14 AND 19 AND {_luhn(value)})"
    if kind == "phone":
        return f"(length({_digits(value)}) BETWEEN 10 AND 15)"
    return "true"


def _may_match(text: str, needs: str, base: bool) -> str:
    """Whether a text holds what a pattern needs."""
    if base:
        return f"contains({text}, '{needs}')" if needs else _like(text, "[0-9]")
    own = _like(text, needs)
    return f"(({_like(text, '[0-9]')} OR contains({text}, '-----BEGIN')) AND {own})" if "0-9" in needs else own


def _named(value: str, name: str, use: str) -> str:
    """use, in which name stands for value, computed once: the only element of an array has a name."""
    return f"element_at(transform(array({value}), {name} -> {use}), 1)"


def _scan(items: str, item: str, carry: dict[str, str], step: dict[str, str], given: str) -> str:
    """What is given for the items one after another, as one array of item (a type).

    carry: what is carried along and begins with; step: its next value; given: an array of items. Both speak of the carry s
    and the item m. Goes in chunks, so that the arrays which grow stay short.
    """
    none, many = f"CAST(array() AS array<{item}>)", f"CAST(array() AS array<array<{item}>>)"

    def state(own: dict[str, str], rest: str) -> str:
        return "named_struct(" + ", ".join(f"'{n}', {x}" for n, x in own.items()) + f", 'out', {rest})"

    one = f"aggregate(some, {state({n: f'c.{n}' for n in carry}, none)}, (s, m) -> {state(step, f'concat(s.out, {given})')})"
    chunk = _named(one, "i", state({n: f"i.{n}" for n in carry}, "concat(c.out, array(i.out))"))
    chunks = f"transform(sequence(0, CAST(floor((size(al) - 1) / {CHUNK}) AS INT)), k -> slice(al, k * {CHUNK} + 1, {CHUNK}))"
    run = f"IF(size(al) > 0, flatten(aggregate({chunks}, {state(carry, many)}, (c, some) -> {chunk}).out), {none})"
    return _named(items, "al", run)


ZERO = "CAST(0 AS BIGINT)"


def _pairs(text: str, pattern: str, may: str) -> str:
    """Matches between their gaps."""
    made = f"transform(regexp_extract_all({text}, {_raw(pattern)}, 0), (v, i) -> named_struct('v', v, 'g', get(gaps, i), 'h', get(gaps, i + 1)))"
    return f"IF({may}, {_named(f'split({text}, {_raw(pattern)}, -1)', 'gaps', made)}, array())"


def _placed(pairs: str) -> str:
    """Array of (start, stop, value, pre, post) in order: pre and post are what is around a match."""
    item = "struct<start: bigint, stop: bigint, value: string, pre: string, post: string>"
    start, stop = "(s.at + length(m.g))", "(s.at + length(m.g) + length(m.v))"
    return _scan(pairs, item, {"at": ZERO}, {"at": stop}, f"array(named_struct('start', {start}, 'stop', {stop}, 'value', m.v, 'pre', right(m.g, 40), 'post', left(m.h, 2)))")


def _vote(yes: str, no: str) -> str:
    return f"CASE WHEN {no} THEN -1 WHEN {yes} THEN 1 ELSE 0 END"


def _variety(value: str) -> str:
    """How many different characters a value holds."""
    return f"size(array_distinct(split({value}, '')))"


def votes(kind: str, base: bool) -> list[str]:
    """One vote of each labeler on the match m."""
    value, left, right, digits = "m.value", "lower(m.pre)", "m.post", _digits("m.value")
    n, own = f"length({digits})", str(base).lower()
    like = lambda pattern: _like(value, pattern)
    shape = {
        "email": lambda: _vote(f"({own} OR {like(r'(?i)[(\[]\s?at\s?[)\]]|\sdot\s')})", f"(length({value}) < 6 OR {like(r'@[^.]*$|\.\x20')})"),
        "ip": lambda: _vote(f"({own} OR {like(r'dot|[\[(]\.|(?::[0-9A-Fa-f]{0,4}){4}')})", f"(NOT {like('[0-9]')} OR {like(r'^[0-9]{1,2}:[0-9]{2}(?::[0-9]{2})?$|^0+[:.]|(?:\.[0-9]+){4}$|[0-9]{4}\.|\.[0-9]{4}')})"),
        "card": lambda: _vote(f"({n} BETWEEN 13 AND 19 AND NOT {like(r'[\x20./_-].*?[0-9]{5}')} AND NOT {like(r'[\x20./_-]{2}')})", f"({_variety(digits)} < 3 OR {n} NOT BETWEEN 13 AND 19)"),
        "phone": lambda: _vote(like(r"^(?:[+(]|00|0[1-9])"), like(r"^(?:19|20)[0-9]{2}[./-][0-9]{2}(?:[./-][0-9]{2})?$|^[0-9]{2}[./-][0-9]{2}[./-](?:19|20)?[0-9]{2}$|^[0-9]+\.[0-9]+$")),
        "secret": lambda: _vote(like(r"^(?:[0-9A-Fa-f]{32,}|[A-Z0-9]{16,}|-----BEGIN)|^(?=.*?[a-z])(?=.*?[A-Z])(?=.*?[0-9]).{16,}$|^[a-z0-9]{16,}$"), f"({n} = length({value}) OR {like(r'^[0-9./_+-]+$|^(?:[A-Za-z]+|[0-9]+)(?:[-_/+](?:[A-Za-z]+|[0-9]+))+$')})"),
    }[kind]()
    check = {
        "email": lambda: _vote(f"({like(r'[A-Za-z]{2,}$')} AND NOT {like('@[^.]*$')})", like(r"[0-9-]$|@[^.]*$")),
        "ip": lambda: _vote(base_check("ip", value), "false") if base else _vote(like(r"^(?=(?:[^:]*+:){2,7}[^:]*+$)(?:(?:[0-9A-Fa-f]{1,4}:){7}[0-9A-Fa-f]{1,4}|(?!.*::.*::)(?=.*::).*)$|^(?:(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])(?:[^0-9]+|$)){4}$"), like(r"^[0-9]{1,2}:[0-9]{2}(?::[0-9]{2})?$|(?:2[6-9][0-9]|25[6-9]|[3-9][0-9]{2}|[0-9]{4,})(?:\.|$)|(?:\.[0-9]+){4}$")),
        "card": lambda: _vote(_luhn(value), f"NOT {_luhn(value)}"),
        "phone": lambda: _vote(f"{n} BETWEEN 10 AND 15", f"{n} NOT BETWEEN 8 AND 15"),
        "secret": lambda: _vote(f"{_variety(f'left({value}, 64)')} >= 9", f"{_variety(f'left({value}, 64)')} <= 5"),
    }[kind]()
    low = f"lower({value})"
    gazetteer = {
        "email": lambda: _vote(_like(low, rf"(?:\.|dot[)\]]?)\x20?(?:{DOMAINS})$"), _like(low, r"localhost|\.(?:png|jpe?g|gif|js|css)$")),
        "ip": lambda: _vote(f"({own} AND NOT {like(r'^(?:0|127|255)\.')})", like(r"^(?:0|255)\.|^(?:0*:){7}|^::$")),
        "card": lambda: _vote(_like(digits, r"^(?:4[0-9]{12}(?:[0-9]{3}){0,2}|(?:5[1-5]|2[2-7])[0-9]{14}|3[47][0-9]{13}|6[0-9]{15,18})$"), _like(digits, "^[01789]")),
        "phone": lambda: _vote(_like(digits, r"^(?:00)?(?:1|3[0-9]|4[0-9])?0?[2-9][0-9]{2}[2-9]"), _like(digits, "^0{2}0|^(?:19|20)[0-9]{6}$")),
        "secret": lambda: _vote(like(rf"^(?:{KEYS})"), _like(low, DUMMIES)),
    }[kind]()
    context = _vote(_like(left, rf"(?:^|[^a-z])(?:{NEAR[kind]})[^a-z0-9]{{0,12}}$"), _like(left, rf"(?:^|[^a-z])(?:{AGAINST})[^a-z0-9]{{0,4}}$"))
    edges = _vote(f"({_like(left, r'[\s(\[<:,;=\x22\x27]$')} OR {left} = '') AND ({_like(right, r'^(?:[\s)\]>,;!?\x22\x27]|\.(?:\s|$))')} OR {right} = '')", f"({_like(left, r'[\p{L}\p{N}]$')} OR {_like(right, r'^[\p{L}\p{N}@]')})")
    return [shape, check, gazetteer, context, edges]


def span_features() -> list[str]:
    """FEATURES of the match m with the votes x, each from 0 up."""
    word = f"regexp_extract(lower(m.pre), {_raw(r'([\p{L}]+)[^\p{L}]*$')}, 1)"
    return [
        "least(6, greatest(0, floor(log2(length(m.value))) - 1))",
        f"floor(4 * length({_digits('m.value')}) / length(m.value))",
        f"least(3, length(regexp_replace(m.value, {_raw('[A-Za-z0-9]')}, '')))",
        "3 * x[0] + x[1] + 4",
        _named(word, "w", "IF(w = '', 4, pmod(crc32(CAST(w AS BINARY)), 4))"),
        f"CASE WHEN {_like('m.post', r'^$|^\s')} THEN 0 WHEN {_like('m.post', r'^[\p{L}\p{N}]')} THEN 2 ELSE 1 END",
    ]


def _candidate(kind: str, base: bool) -> str:
    pattern = reduce(lambda a, i: f"({a} * 3 + x[{i}] + 1)", range(len(LABELERS)), "0")
    fields = {"start": "m.start", "kind": f"{KINDS.index(kind)}", "stop": "m.stop", "base": str(base).lower(), "votes": f"CAST({pattern} AS SMALLINT)"}
    fields |= {n: f"CAST({f} AS TINYINT)" for n, f in zip(FEATURES, span_features(), strict=True)}
    return _named(f"array({', '.join(votes(kind, base))})", "x", "named_struct(" + ", ".join(f"'{n}', {f}" for n, f in fields.items()) + ")")


CANDIDATE = "struct<start: bigint, kind: int, stop: bigint, base: boolean, votes: smallint, " + ", ".join(f"{n}: tinyint" for n in FEATURES) + ">"


def _clear_of_base(spans: str) -> str:
    """Sorted candidates without those that overlap a base span: one scan forwards, one back."""
    only = lambda keep: f"IF(m.base OR {keep}, array(m), CAST(array() AS array<{CANDIDATE}>))"
    ahead = _scan(spans, CANDIDATE, {"reach": ZERO}, {"reach": "IF(m.base, greatest(s.reach, m.stop), s.reach)"}, only("m.start >= s.reach"))
    back = _scan(f"reverse({ahead})", CANDIDATE, {"next": "CAST(9223372036854775807 AS BIGINT)"}, {"next": "IF(m.base, least(s.next, m.start), s.next)"}, only("m.stop <= s.next"))
    return f"reverse({back})"


def _searched(docs: DataFrame, text_col: str, keep: list[str]) -> DataFrame:
    """row (a struct of the columns to keep) and spans: every candidate with its votes and features."""
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in keep)).alias("row"), F.coalesce(F.col(f"`{text_col}`").cast("string"), F.lit("")).alias("body"))
    found = {f"{kind}_{base}".lower(): (kind, base, *own) for table_, base in ((BASE, True), (WIDER, False)) for kind, own in table_.items()}
    rows = rows.selectExpr("*", *(f"{_pairs('body', pattern, _may_match('body', needs, base))} AS {n}" for n, (_, base, pattern, needs) in found.items()))
    rows = rows.selectExpr("row", *(f"{_placed(n)} AS {n}" for n in found))
    lists = [f"transform(filter({n}, m -> {base_check(kind, 'm.value') if base else 'true'}), m -> {_candidate(kind, base)})" for n, (kind, base, _, _) in found.items()]
    return rows.selectExpr("row", f"array_sort(concat({', '.join(lists)})) AS spans").selectExpr("row", f"{_clear_of_base('spans')} AS spans")


def candidates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id_col and spans: base ones that pass their check, and wider ones that overlap none of these, in order."""
    return _searched(docs, text_col, [id_col]).select("row.*", "spans")


class SpanClassifier:
    """Per kind: a bias and a weight for each value of each feature."""

    def __init__(self, weights: dict[int, list[float]]):
        self.weights = weights

    def logit(self, span: str) -> str:
        """As SQL over a span."""
        cases = []
        for kind, (bias, *rest) in self.weights.items():
            total, at = [f"{float(bias)!r}D"], 0
            for name, size in FEATURES.items():
                own = ", ".join(f"{float(x)!r}D" for x in rest[at : at + size])
                total, at = [*total, f"get(array({own}), CAST({span}.{name} AS INT))"], at + size
            cases.append(f"WHEN {kind} THEN {' + '.join(total)}")
        return f"(CASE {span}.kind {' '.join(cases)} ELSE -30.0D END)" if cases else "-30.0D"

    def accepts(self, span: str) -> str:
        margin = " + ".join(f"pmod(CAST({span}.votes / {3**i} AS INT), 3)" for i in range(len(LABELERS)))
        return f"({margin} >= {MARGIN + len(LABELERS)} AND {self.logit(span)} >= {math.log(ACCEPT / (1 - ACCEPT))!r}D)"


def reliabilities(table_: list[tuple[tuple[int, ...], int]], rounds: int = 50) -> tuple[float, list[list[list[float]]], list[float]]:
    """Expectation-maximisation over (votes, count): the share of true spans, P(vote | truth) and posteriors."""
    total = sum(n for _, n in table_)
    post = [1 / (1 + math.exp(-1.5 * sum(v) + 1.0)) for v, _ in table_]
    share, chance = 0.5, []
    for _ in range(rounds):
        mass = [sum(n * (1 - p) for (_, n), p in zip(table_, post)), sum(n * p for (_, n), p in zip(table_, post))]
        share = (mass[1] + 1) / (total + 2)
        chance = [[[(sum(n * (p if y else 1 - p) for (v, n), p in zip(table_, post) if v[i] == vote) + (2 if vote == (1 if y else -1) else 1)) / (mass[y] + 4) for vote in (-1, 0, 1)] for y in (0, 1)] for i in range(len(LABELERS))]
        post = []
        for v, _ in table_:
            z = math.log(share / (1 - share)) + sum(math.log(chance[i][1][x + 1] / chance[i][0][x + 1]) for i, x in enumerate(v))
            post.append(1 / (1 + math.exp(-max(-30, min(30, z)))))
    return share, chance, post


def unpacked(pattern: int) -> tuple[int, ...]:
    """The votes in a pattern's number."""
    out = []
    for _ in LABELERS:
        pattern, vote = divmod(pattern, 3)
        out.append(vote - 1)
    return tuple(reversed(out))


def fit_logistic(table_: list[tuple[tuple[int, ...], int, float]], steps: int = 30, shrink: float = 0.5) -> list[float]:
    """Logistic regression on (features, spans, sum of their posteriors), by damped Newton steps with a small penalty."""
    sizes = list(FEATURES.values())
    begins = np.concatenate(([1], 1 + np.cumsum(sizes)[:-1]))
    x = np.zeros((len(table_), 1 + sum(sizes)))
    x[:, 0] = 1
    for i, (values, _, _) in enumerate(table_):
        x[i, begins + np.array(values)] = 1
    n, p = np.array([r[1] for r in table_], float), np.array([r[2] for r in table_], float)
    w, penalty = np.zeros(x.shape[1]), np.full(x.shape[1], shrink)
    penalty[0] = 1e-3
    for _ in range(steps):
        q = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        slope = x.T @ (n * q - p) + penalty * w
        bend = (x * (n * np.maximum(q * (1 - q), 1e-6))[:, None]).T @ x + np.diag(penalty)
        step = np.linalg.solve(bend, slope)
        w = w - step * min(1.0, 4.0 / max(1e-9, float(np.abs(step).max())))
    return w.tolist()


PATTERNS = 3 ** len(LABELERS)
#: Posteriors are summed as whole numbers, so sums don't depend on the order of rows.
WHOLE = 1_000_000


def fit(spans: DataFrame) -> SpanClassifier:
    """From candidates(): vote patterns and then features are counted over all rows.

    The driver gets at most KINDS * 3^5 and then KINDS * FEATURE_PATTERNS rows.
    """
    one = spans.select(F.explode("spans").alias("s"))
    counts = one.groupBy("s.kind", "s.votes").count().collect()
    post = [0] * (len(KINDS) * PATTERNS)
    for kind in range(len(KINDS)):
        rows = sorted((r["votes"], r["count"]) for r in counts if r["kind"] == kind)
        if rows:
            for (v, _), p in zip(rows, reliabilities([(unpacked(v), n) for v, n in rows])[2], strict=True):
                post[kind * PATTERNS + v] = round(p * WHOLE)
    soft = F.expr(f"get(CAST(split('{','.join(map(str, post))}', ',') AS array<bigint>), s.kind * {PATTERNS} + s.votes)")
    table_ = one.groupBy("s.kind", *(f"s.{f}" for f in FEATURES)).agg(F.count(F.lit(1)).alias("n"), F.sum(soft).alias("p")).collect()
    weights = {}
    for kind in range(len(KINDS)):
        if rows := sorted((tuple(r[f] for f in FEATURES), r["n"], r["p"] / WHOLE) for r in table_ if r["kind"] == kind):
            weights[kind] = fit_logistic(rows)
    return SpanClassifier(weights)


PLAIN = "named_struct('start', m.start, 'kind', m.kind, 'stop', m.stop)"


def accepted(model: SpanClassifier, spans: str) -> str:
    """As SQL: base spans, and those accepted of the others that overlap none accepted before, in order."""
    chosen = f"filter({spans}, m -> m.base OR {model.accepts('m')})"
    further = "(NOT m.base AND m.start >= s.reach)"
    return _scan(chosen, SPAN, {"reach": ZERO}, {"reach": f"IF({further}, m.stop, s.reach)"}, f"IF(m.base OR {further}, array({PLAIN}), CAST(array() AS array<{SPAN}>))")


def _joined(spans: str) -> str:
    names = ", ".join(f"'{k}'" for k in KINDS)
    return f"array_join(transform({spans}, m -> concat_ws(':', get(array({names}), m.kind), m.start, m.stop)), ',')"


def find_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id_col, spans (all) and base: arrays of (start, kind, stop), kind as an index into KINDS."""
    found = materialize(candidates(docs, id_col, text_col), "pii-candidates")
    return found.select(id_col, F.expr(accepted(fit(found), "spans")).alias("spans"), F.expr(f"transform(filter(spans, m -> m.base), m -> {PLAIN})").alias("base"))


def cut(text: str, spans: str) -> str:
    """As SQL: text with [KIND] in place of the spans; spans that overlap become one mark, that of the first.

    Pieces are cut from the part of the text that a chunk of CHUNK marks covers, so many marks don't each walk the whole text.
    """
    item = "struct<begin: bigint, until: bigint, kind: int>"
    one = "array(named_struct('begin', s.reach, 'until', m.start, 'kind', m.kind))"
    gaps = _scan(spans, item, {"reach": ZERO}, {"reach": "greatest(s.reach, m.stop)"}, f"IF(m.start >= s.reach, {one}, CAST(array() AS array<{item}>))")
    marks = ", ".join(f"'[{k.upper()}]'" for k in KINDS)
    part = f"substring({text}, CAST(some[0].begin + 1 AS INT), CAST(element_at(some, -1).until - some[0].begin AS INT))"
    piece = f"concat(substring(part, CAST(g.begin - some[0].begin + 1 AS INT), CAST(g.until - g.begin AS INT)), get(array({marks}), g.kind))"
    chunk = _named(part, "part", f"array_join(transform(some, g -> {piece}), '')")
    head = _named(gaps, "al", f"array_join(transform(sequence(0, CAST(floor((size(al) - 1) / {CHUNK}) AS INT)), k -> {_named(f'slice(al, k * {CHUNK} + 1, {CHUNK})', 'some', chunk)}), '')")
    tail = f"substring({text}, CAST(array_max(transform({spans}, m -> m.stop)) + 1 AS INT))"
    return f"IF(size({spans}) > 0, concat({head}, {tail}), {text})"


def redact(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """docs with every span that find_spans() gives replaced by [KIND]; other columns stay.

    Texts are searched once; rows go with their spans into a table, from which the classifier is fitted and texts are cut.
    """
    found = materialize(_searched(docs, text_col, docs.columns), "pii-candidates")
    out = found.select("row", F.expr(accepted(fit(found), "spans")).alias("spans"))
    return out.select(*(F.expr(cut(f"row.`{c}`", "spans") if c == text_col else f"row.`{c}`").alias(c) for c in docs.columns))


def op1_private_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_spans(table(spark, sf_dir, "documents"))
    of_kind = [f"CAST(size(filter({'base' if k < 4 else 'spans'}, m -> m.kind = {k})) AS BIGINT) AS n_{name}" for k, name in enumerate(KINDS)]
    return found.selectExpr("doc_id", *of_kind[:4], f"sha2({_joined('base')}, 256) AS base_sha256", f"{_joined('spans')} AS spans", of_kind[4], "CAST(size(spans) AS BIGINT) AS n_spans")
