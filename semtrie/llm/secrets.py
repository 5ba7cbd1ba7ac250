"""Secret scan: pattern spans plus sliding-window entropy spans, all in DataFrame functions.

Defined cases: a null or empty text has no spans; spans are in code points, end
exclusive; equal starts are ordered by kind as listed in ``KINDS``; repeated rows
give repeated results; other columns are passed through untouched.
"""

from __future__ import annotations

import functools
import math
import operator

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KINDS = ("assign", "access", "hex", "entropy_hex", "entropy_text")

# Fixed values of the base rules.
ASSIGN = r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{14,}"
HEX = r"[0-9a-f]{16,}"

HEX_SYMBOLS = "0123456789abcdef"
TEXT_SYMBOLS = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_-="
SCALE = 1 << 20

#: Candidates that match one of these are never reported by the entropy rules.
ALLOW_LIST = (
    r"^[A-Za-z_=/+-]*$",
    r"^[0-9_=/+-]*$",
    r"(?i)example|placeholder|changeme|x{6,}",
    r"(?i)0123456789|abcdefghij",
    r"^[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}$",
)


#: Elements of a block in running values; the blocks' own values make a second, shorter run.
RUN = 256


def _let(value: Column, use) -> Column:
    """``use(value)`` with the value worked out once, however often it is used."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def _running(values: Column, join, zero: Column) -> Column:
    """For each element what ``join`` (sum, maximum) makes of all elements before it.

    Run block by block: appending to one array would copy it once per element.
    """

    def run(block, start):
        grown = F.aggregate(block, F.array(start), lambda acc, x: F.concat(acc, F.array(join(F.element_at(acc, F.lit(-1)), x))))
        return F.slice(grown, F.lit(1), F.size(block))

    def blocks_of(v):
        return F.transform(F.sequence(F.lit(0), F.floor((F.size(v) - 1) / RUN).cast("int")), lambda b: F.slice(v, b * RUN + 1, F.lit(RUN)))

    def over(blocks):
        whole = F.transform(blocks, lambda block: F.aggregate(block, zero, join))
        starts = _let(whole, lambda w: F.aggregate(w, F.array(zero), lambda acc, x: F.concat(acc, F.array(join(F.element_at(acc, F.lit(-1)), x)))))
        return _let(starts, lambda at: F.flatten(F.transform(blocks, lambda block, i: run(block, F.get(at, i)))))

    return _let(values, lambda v: F.when(F.size(v) == 0, v).otherwise(_let(blocks_of(v), over)))


def _located(text: Column, pattern: str, groups: dict[str, int]) -> Column:
    """Array of (start, end, one string per group) of the leftmost non-overlapping matches.

    The engine has no match positions: the texts between matches (``split``) and
    the matches themselves alternate, so their running lengths are the positions.
    """
    regex = F.lit(pattern)
    between = F.split(text, pattern, -1)
    columns = [F.transform(between, lambda p: F.char_length(p)).alias("gap"), F.regexp_extract_all(text, regex, F.lit(0)).alias("whole")]
    columns += [F.regexp_extract_all(text, regex, F.lit(g)).alias(name) for name, g in groups.items()]
    zipped = F.filter(F.arrays_zip(*columns), lambda m: m["whole"].isNotNull())
    kind = "array<struct<" + ",".join(["start:int", "end:int", *(f"{name}:string" for name in groups)]) + ">>"

    def place(found):
        steps = F.transform(found, lambda m: m["gap"] + F.char_length(m["whole"]))
        ends = _running(steps, lambda a, b: a + b, F.lit(0))
        return F.zip_with(found, ends, lambda m, at: F.struct((at + m["gap"]).alias("start"), (at + m["gap"] + F.char_length(m["whole"])).alias("end"), *(m[name].alias(name) for name in groups)))

    return F.when(text.rlike(pattern), _let(zipped, place).cast(kind)).otherwise(F.array().cast(kind))


def _spans(hits: Column, order: int) -> Column:
    return F.transform(hits, lambda h: F.struct(h["start"].alias("start"), F.lit(order).alias("kind"), h["end"].alias("end")))


def entropy_units(window: int, bits: float) -> int:
    """The entropy threshold as a bound on the scaled sum of c * log2(c) over a window's counts."""
    return int(math.floor(window * (math.log2(window) - bits) * SCALE))


def count_weights(window: int) -> list[int]:
    return [0] + [round(c * math.log2(c) * SCALE) for c in range(1, window + 1)]


def _windows(candidate: Column, symbols: str, window: int, bits: float) -> Column:
    """First start and last end of the windows whose Shannon entropy reaches ``bits`` (null if none does).

    One pass over the characters, whatever their number; the counts and the sum
    of c * log2(c) change by the entering and the leaving character only.  The sum is kept in scaled
    integers so that the running value never drifts.
    """
    weights = count_weights(window)
    gain = F.array(*[F.lit(y - x).cast("long") for x, y in zip(weights, weights[1:], strict=False)])  # what a count adds as it grows by one
    at_most = entropy_units(window, bits)
    # a count takes ``wide`` bits and a long holds ``per`` of them, so that a step rewrites a few longs
    wide = window.bit_length()
    per = 62 // wide
    none = F.lit(0).cast("long")
    unit = lambda c: F.call_function("shiftleft", F.lit(1).cast("long"), c["shift"])
    count_of = lambda counts, c: F.call_function("shiftright", F.get(counts, c["slot"]), c["shift"]).bitwiseAND(F.lit((1 << wide) - 1)).cast("int")
    kind = "struct<counts:array<bigint>,total:bigint,at:int,first:int,last:int>"
    zero = F.struct(F.array_repeat(none, len(symbols) // per + 1).alias("counts"), none.alias("total"), F.lit(0).alias("at"), F.lit(-1).alias("first"), F.lit(-1).alias("last")).cast(kind)
    # a window is judged from the state it left, so that its sum is worked out once
    good = lambda state: (state["at"] >= window) & (state["total"] <= at_most)
    first = lambda state: F.when((state["first"] < 0) & good(state), state["at"] - window).otherwise(state["first"])
    last = lambda state: F.when(good(state), state["at"]).otherwise(state["last"])

    def step(state, pair):
        new, old = pair["enters"], pair["leaves"]
        grown = state["total"] + F.get(gain, count_of(state["counts"], new))
        # a character that enters and leaves at once changes nothing
        total = F.when(old.isNull(), grown).when(new == old, state["total"]).otherwise(grown - F.get(gain, count_of(state["counts"], old) - 1))
        counts = F.transform(state["counts"], lambda c, k: c + F.when(k == new["slot"], unit(new)).otherwise(none) - F.when(k == old["slot"], unit(old)).otherwise(none))
        return F.struct(counts.alias("counts"), total.alias("total"), (state["at"] + 1).alias("at"), first(state).alias("first"), last(state).alias("last")).cast(kind)

    def scan(codes):
        # each character beside the one that leaves the window as it enters
        n = F.size(codes)
        leaves = F.slice(F.concat(F.array_repeat(F.lit(None).cast("struct<slot:int,shift:int>"), window), codes), F.lit(1), n)
        return F.aggregate(F.arrays_zip(codes.alias("enters"), leaves.alias("leaves")), zero, step, lambda run: F.struct(first(run).alias("first"), last(run).alias("last")))

    # the characters as places among the symbols, once: a character's place in a long string is found by walking there
    places = F.transform(F.filter(F.split(candidate, "", -1), lambda c: c != ""), lambda c: F.instr(F.lit(symbols), c))
    coded = F.transform(places, lambda c: F.struct(F.floor(c / per).cast("int").alias("slot"), (F.pmod(c, F.lit(per)) * wide).alias("shift")))
    return F.when(F.char_length(candidate) >= window, _let(coded, scan))


def _entropy(text: Column, pattern: str, symbols: str, window: int, bits: float, allow: tuple[str, ...], fold: bool) -> Column:
    candidates = _located(text, pattern, {"body": 0})
    if allow:
        candidates = F.filter(candidates, lambda h: ~functools.reduce(operator.or_, [h["body"].rlike(rule) for rule in allow]))
    marked = F.transform(candidates, lambda h: F.struct(h["start"].alias("start"), _windows(F.lower(h["body"]) if fold else h["body"], symbols, window, bits).alias("run")))
    good = F.filter(marked, lambda h: h["run"]["first"] >= 0)
    return F.transform(good, lambda h: F.struct((h["start"] + h["run"]["first"]).alias("start"), (h["start"] + h["run"]["last"]).alias("end")))


def find_secrets(
    df: DataFrame,
    text_col: str = "text",
    *,
    window: int = 20,
    hex_bits: float = 3.0,
    text_bits: float = 3.75,
    allow: tuple[str, ...] = ALLOW_LIST,
) -> DataFrame:
    """Add ``base_spans`` and ``all_spans``, arrays of (start, kind, end) with kind an index into ``KINDS``.

    Base rules: keyword assignments with a value of 12 or more characters, access
    ids of 18 or more, hex runs of 16 or more.  Added rules: within strings of at
    least ``window`` characters of one class (hex digits; base64-like characters),
    the stretch from the first to the last window whose Shannon entropy reaches
    the class's threshold, unless the string is on the allow list or the stretch
    lies inside a base span.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    staged = df.select(
        "*",
        F.filter(_located(text, ASSIGN, {"value": 2}), lambda h: F.char_length(h["value"]) >= 12).alias("__assign"),
        _located(text, ACCESS, {}).alias("__access"),
        _located(text, HEX, {}).alias("__hex"),
        _entropy(text, r"[0-9A-Fa-f]{%d,}" % window, HEX_SYMBOLS, window, hex_bits, allow, True).alias("__eh"),
        _entropy(text, r"[A-Za-z0-9+/_=-]{%d,}" % window, TEXT_SYMBOLS, window, text_bits, allow, False).alias("__et"),
    )
    base = F.concat(_spans(F.col("__assign"), 0), _spans(F.col("__access"), 1), _spans(F.col("__hex"), 2))
    staged = staged.withColumn("base_spans", F.array_sort(base)).drop("__assign", "__access", "__hex")
    added = F.concat(_spans(F.col("__eh"), 3), _spans(F.col("__et"), 4))
    # in order of start, the farthest end of the base spans so far tells whether a span lies inside one of them
    tagged = F.array_sort(F.concat(
        F.transform("base_spans", lambda b: F.struct(b["start"].alias("start"), F.lit(0).alias("added"), b["kind"].alias("kind"), b["end"].alias("end"))),
        F.transform(added, lambda a: F.struct(a["start"].alias("start"), F.lit(1).alias("added"), a["kind"].alias("kind"), a["end"].alias("end"))),
    ))

    def uncovered(spans):
        farthest = _running(F.transform(spans, lambda x: F.when(x["added"] == 0, x["end"]).otherwise(-1)), lambda a, b: F.greatest(a, b), F.lit(-1))
        judged = F.zip_with(spans, farthest, lambda x, f: F.when((x["added"] == 1) & (f < x["end"]), F.struct(x["start"].alias("start"), x["kind"].alias("kind"), x["end"].alias("end"))))
        return F.filter(judged, lambda x: x.isNotNull())

    fresh = F.when((F.size("__eh") > 0) | (F.size("__et") > 0), _let(tagged, uncovered))
    every = F.when(fresh.isNull(), F.col("base_spans")).otherwise(F.array_sort(F.concat("base_spans", fresh)))
    return staged.withColumn("all_spans", every).drop("__eh", "__et")


def spans_text(spans: Column) -> Column:
    """``kind:start:end`` joined by commas."""
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"], s["end"])), ",")


def op6_secret_scan(spark, sf_dir) -> DataFrame:
    """Contract query of operator 6 over every whole text of ``documents``."""
    from semtrie.llm.common import table

    found = find_secrets(table(spark, sf_dir, "documents").select("doc_id", "text"))
    count = lambda k: F.size(F.filter("base_spans", lambda s: s["kind"] == k)).cast("long")
    return found.select(
        "doc_id",
        count(0).alias("n_assign"),
        count(1).alias("n_access"),
        count(2).alias("n_hex"),
        F.sha2(spans_text(F.col("base_spans")), 256).alias("base_sha256"),
        spans_text(F.col("all_spans")).alias("spans"),
    )


def _located_sql(order: int, pattern: str, group: int, test: str) -> str:
    """Rows (doc_id, k, body, a, b) of one pattern: spans from the lengths of matches and of the texts between."""
    p = pattern.replace("'", "''")
    return f"""SELECT doc_id, {order} AS k, m[i] AS body, a, a + length(m[i]) AS b FROM (
    SELECT *, CAST(list_sum(list_transform(gap[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(m[1:i - 1], lambda x: length(x))), 0) AS BIGINT) AS a FROM (
      SELECT doc_id, m, g, gap, unnest(range(1, len(m) + 1)) AS i FROM (
        SELECT doc_id, regexp_extract_all(s, '{p}') AS m, regexp_extract_all(s, '{p}', {group}) AS g, string_split_regex(s, '{p}') AS gap FROM t WHERE regexp_matches(s, '{p}')))) WHERE {test}"""


def _entropy_sql(order: int, pattern: str, window: int, bits: float, fold: bool) -> str:
    body = "lower(body)" if fold else "body"
    part = f"string_split(substr({body}, CAST(j + 1 AS INT), {window}), '')"
    total = f"list_sum(list_transform(list_distinct({part}), lambda ch: {count_weights(window)}[len(list_filter({part}, lambda x: x = ch)) + 1]))"
    allowed = " OR ".join("regexp_matches(body, '{}')".format(a.replace("'", "''")) for a in ALLOW_LIST)
    return f"""SELECT doc_id, k, a + good[1] AS a, a + good[-1] + {window} AS b FROM (
    SELECT *, list_filter(range(0, length(body) - {window - 1}), lambda j: {total} <= {entropy_units(window, bits)}) AS good
    FROM ({_located_sql(order, pattern, 0, "true")}) WHERE NOT ({allowed})) WHERE len(good) > 0"""


OP6_SQL = f"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS s FROM documents),
base AS MATERIALIZED (
  SELECT doc_id, k, a, b FROM (
  {_located_sql(0, ASSIGN, 2, "length(g[i]) >= 12")}
  UNION ALL {_located_sql(1, ACCESS, 0, "true")}
  UNION ALL {_located_sql(2, HEX, 0, "true")})),
added AS MATERIALIZED (
  {_entropy_sql(3, "[0-9A-Fa-f]{20,}", 20, 3.0, True)}
  UNION ALL {_entropy_sql(4, "[A-Za-z0-9+/_=-]{20,}", 20, 3.75, False)}),
every AS (
  SELECT * FROM base UNION ALL SELECT * FROM added d WHERE NOT EXISTS (SELECT 1 FROM base e WHERE e.doc_id = d.doc_id AND e.a <= d.a AND d.b <= e.b)),
named AS (SELECT *, {list(KINDS)}[k + 1] || ':' || a || ':' || b AS name FROM every)
SELECT t.doc_id, CAST(count(*) FILTER (WHERE k = 0) AS BIGINT) AS n_assign, CAST(count(*) FILTER (WHERE k = 1) AS BIGINT) AS n_access, CAST(count(*) FILTER (WHERE k = 2) AS BIGINT) AS n_hex,
  sha256(coalesce(string_agg(name, ',' ORDER BY a, k, b) FILTER (WHERE k <= 2), '')) AS base_sha256, coalesce(string_agg(name, ',' ORDER BY a, k, b), '') AS spans
FROM t LEFT JOIN named ON named.doc_id = t.doc_id GROUP BY t.doc_id
"""
