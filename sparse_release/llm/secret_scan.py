"""Secret scans with multipart credential linking.

Strong spans are found by pattern alone. Weak candidates (an account name, a random-looking token, an endpoint) mean nothing by themselves; they are
reported only when the complementary parts of a credential stand within one scope: identifier and secret for both of these, and both for an endpoint.
The interval join of parts is a matter of running maxima and minima over each text's parts in order of their place, inside the row: no shuffle, no Python. Running
values are taken by doubling steps, so a text with n spans costs n log n.

Offsets are code points, ends exclusive. Null text: as empty, no spans. Rows are scanned each for itself, so repeated rows and ids give equal
results; an empty table gives an empty one. Other columns pass through whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fresh

#: kind, pattern (Java regex), least length of the match or, for `assign` and `part_id`, of its second group. Ranks follow this order.
KINDS: tuple[tuple[str, str, int], ...] = (
    ("assign", r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 6),
    ("access", r"AKIA[A-Z0-9]+", 20),
    ("hex", r"[0-9a-f]{24,}", 24),
    ("part_secret", r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{32,}", 32),
    ("part_id", r"""(?i)\b(user_?name|user_?id|login|account_?id|client_?id|key_?id)["']?\x20*[:=]\x20*["']?([A-Za-z0-9._@-]+)""", 3),
    ("part_endpoint", r"(?i)\b(?:https?|wss?|ftp|s3|jdbc:[a-z]+|postgres(?:ql)?|mysql|mongodb|redis|amqp)://[A-Za-z0-9._~:/?#@!&=+%-]+", 8),
)
N_BASE = 3

#: Two parts are in one scope if they start at most so many code points apart.
SCOPE = 400

#: What takes the place of a secret; code points of the pieces that a text is cut into for that.
MASK, PIECE = "[SECRET]", 4096

_SPAN = "struct<s:bigint,k:int,e:bigint>"


def _running(values: str, how: str) -> str:
    """SQL: running sums (`add`), or running `greatest` or `least` that pass nulls over, of an array; each step reaches twice as far back as the one before."""
    reach = "get(x, i - CAST(shiftleft(1, d) AS INT))"
    both = f"v + coalesce({reach}, 0L)" if how == "add" else f"{how}(v, {reach})"
    return f"aggregate(CASE WHEN size({values}) > 1 THEN sequence(0, CAST(ceil(log2(size({values}))) AS INT) - 1) ELSE array() END, {values}, (x, d) -> transform(x, (v, i) -> {both}))"


def _quoted(pattern: str) -> str:
    return "'" + pattern.replace("\\", "\\\\").replace("'", "\\'") + "'"


def secret_spans(docs: DataFrame, text_col: str = "text", scope: int = SCOPE, name: str = "secrets") -> tuple[DataFrame, str]:
    """docs with one more column: struct of `base` and `spans`, arrays of (s, k, e): start, rank of kind, end, in order of start, then kind; and that column's name."""
    text = f"coalesce(`{text_col}`, '')"
    keep = [f"`{c}`" for c in docs.columns]
    raw, parts, walked, out = fresh(docs, "ss_raw", "ss_parts", "ss_walked", name)
    cut = ", ".join(
        f"CASE WHEN {text} RLIKE {(p := _quoted(pattern))} THEN struct(regexp_extract_all({text}, {p}, 0) AS m, split({text}, {p}, -1) AS p) END AS {kind}" for kind, pattern, _ in KINDS
    )
    found = docs.selectExpr(*keep, f"struct({cut}) AS `{raw}`")

    def located(rank: int) -> str:
        kind, pattern, least = KINDS[rank]
        m, p = f"`{raw}`.{kind}.m", f"`{raw}`.{kind}.p"
        value = "regexp_extract(v.m, {}, 2)".format(_quoted(pattern)) if kind in ("assign", "part_id") else "v.m"
        fits = f"length({value}) >= {least}" + (" AND v.m RLIKE '[0-9]' AND v.m RLIKE '[A-Za-z]'" if kind == "part_secret" else "")
        ends = _running(f"transform({m}, (x, i) -> CAST(length(x) + length({p}[i]) AS BIGINT))", "add")
        return f"""CASE WHEN `{raw}`.{kind} IS NULL THEN CAST(array() AS array<{_SPAN}>) ELSE transform(
            filter(zip_with({m}, {ends}, (m, e) -> struct(m, e)), v -> {fits}), v -> struct(v.e - length(v.m) AS s, {rank} AS k, v.e AS e)) END"""

    placed = found.selectExpr(*keep, f"array_sort(concat({', '.join(located(k) for k in range(len(KINDS)))})) AS `{parts}`")
    # Identifiers: access, part_id; secrets: assign, hex, part_secret. For each part, the last start of either up to it and the next one from it on; the furthest
    # end of a base span up to it, and the start of the next.
    at = f"`{parts}`"

    def before(kinds: str, value: str = "s") -> str:
        return _running(f"transform({at}, v -> CASE WHEN v.k IN ({kinds}) THEN v.{value} END)", "greatest")

    def after(kinds: str) -> str:
        return f"reverse({_running(f'transform(reverse({at}), v -> CASE WHEN v.k IN ({kinds}) THEN v.s END)', 'least')})"

    ids, keys, base_kinds = "1, 4", "0, 2, 3", ", ".join(map(str, range(N_BASE)))
    weak = f"exists({at}, v -> v.k >= {N_BASE})"
    running = f"{before(ids)} AS i, {after(ids)} AS i2, {before(keys)} AS x, {after(keys)} AS x2, {before(base_kinds, 'e')} AS b, {after(base_kinds)} AS b2"
    linked = placed.selectExpr(*keep, at, f"CASE WHEN {weak} THEN struct({running}) END AS `{walked}`")
    near = lambda c: f"(coalesce(v.s - `{walked}`.{c}[j] <= {scope}, FALSE) OR coalesce(`{walked}`.{c}2[j] - v.s <= {scope}, FALSE))"
    base = f"filter({at}, v -> v.k < {N_BASE})"
    clear = f"(coalesce(`{walked}`.b[j] <= v.s, TRUE) AND coalesce(`{walked}`.b2[j] >= v.e, TRUE))"
    added = f"filter({at}, (v, j) -> (v.k = 3 AND {near('i')} AND {clear}) OR (v.k = 4 AND {near('x')}) OR (v.k = 5 AND {near('i')} AND {near('x')}))"
    done = linked.selectExpr(*keep, f"struct({base} AS base, CASE WHEN `{walked}` IS NULL THEN {base} ELSE array_sort(concat({base}, {added})) END AS spans) AS `{out}`")
    return done, out


def spelled(spans: str) -> str:
    """SQL: spans as kind:start:end, comma-joined."""
    kinds = "array(" + ", ".join(f"'{k}'" for k, _, _ in KINDS) + ")"
    return f"array_join(transform({spans}, v -> concat_ws(':', {kinds}[v.k], CAST(v.s AS STRING), CAST(v.e AS STRING))), ',')"


def masked(docs: DataFrame, text_col: str = "text", scope: int = SCOPE) -> DataFrame:
    """docs with every span of every secret replaced by MASK; spans that meet are replaced together. Columns as before."""
    rows, col = secret_spans(docs, text_col, scope)
    reach, cuts, parts = fresh(rows, "ss_reach", "ss_cuts", "ss_parts")
    spans, keep = f"`{col}`.spans", [f"`{c}`" for c in rows.columns]
    found = rows.selectExpr(*keep, f"CASE WHEN size({spans}) > 0 THEN {_running(f'transform({spans}, v -> v.e)', 'greatest')} END AS `{reach}`")
    # a cut starts where no span before reaches, and ends where the next does not start within reach
    heads = f"filter({spans}, (v, j) -> coalesce(v.s > get(`{reach}`, j - 1), TRUE))"
    tails = f"filter(`{reach}`, (e, j) -> coalesce(get({spans}, j + 1).s > e, TRUE))"
    found = found.selectExpr(*keep, f"CASE WHEN `{reach}` IS NOT NULL THEN zip_with({heads}, {tails}, (v, e) -> struct(v.s AS s, e AS e)) END AS `{cuts}`")
    # the text in pieces of bounded length, so that a place in it is found without reading all before it
    text = f"`{text_col}`"
    found = found.selectExpr(*keep, f"`{cuts}`", f"CASE WHEN `{cuts}` IS NOT NULL THEN regexp_extract_all({text}, '(?s).{{1,{PIECE}}}', 0) END AS `{parts}`")

    def between(a: str, b: str) -> str:
        first, last = f"CAST({a} div {PIECE} AS INT)", f"CAST({b} div {PIECE} AS INT)"
        head = f"CAST({a} % {PIECE} + 1 AS INT)"
        return f"""CASE WHEN {a} >= {b} THEN '' WHEN {first} = {last} THEN substring(`{parts}`[{first}], {head}, CAST({b} - {a} AS INT))
            ELSE concat(substring(`{parts}`[{first}], {head}), array_join(slice(`{parts}`, {first} + 2, {last} - {first} - 1), ''), coalesce(substring(get(`{parts}`, {last}), 1, CAST({b} % {PIECE} AS INT)), '')) END"""

    kept = f"transform(`{cuts}`, (v, i) -> concat({between(f'coalesce(get(`{cuts}`, i - 1).e, 0L)', 'v.s')}, '{MASK}'))"
    rest = between(f"element_at(`{cuts}`, -1).e", f"CAST(length({text}) AS BIGINT)")
    masked_text = F.expr(f"CASE WHEN `{cuts}` IS NULL THEN {text} ELSE concat(array_join({kept}, ''), {rest}) END")
    return found.select(*[masked_text.alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns])
