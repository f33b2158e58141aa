"""Secret scans in DataFrame expressions only: fixed patterns, and a randomness test battery over encoded-looking runs.

Patterns (kinds assign, access, hex) are matched leftmost and without overlap for each kind. The battery takes every maximal run of 20 or more
characters of the base64 alphabets that no pattern touches, infers its encoding (hex, base32, base64, base64url) and tests the
hypothesis that its symbols are drawn at random: chi-squared uniformity over the alphabet, runs above and below its middle, and
correlation of neighbours; p combines the least of the three as if they were independent. Two limits are set for each band of lengths (powers of two)
from counts over the whole corpus. Benjamini and Hochberg's procedure picks the runs that are surely not random, at a false-discovery rate of
FDR, so a random key is seldom thrown away. And of the runs reported as kind random, at most a share of REPORT_FDR may be other strings: p of random runs
is uniform, their number follows from the runs with large p, and what stands above it near the limit is false; the limit rises until that is rare.

Defined results: null and empty texts have no spans; rows are judged one by one, repeats alike; ties in start are ordered by kind
(assign, access, hex, random); an input column named like a result column is replaced; an empty table gives an empty result.
Offsets are code points, end exclusive. Texts are scanned whole.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import load

KINDS = ("assign", "access", "hex", "random")
ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{12,}"
HEX = r"[0-9a-f]{32,}"
RUN = r"[A-Za-z0-9+/_-]{20,}={0,2}"
MIN_VALUE = 8
FDR = 0.01
#: Share of the reported runs that may be false, and the p above which (nearly) only random runs lie, as a bin.
REPORT_FDR, SURE_BIN = 0.1, 3
#: Matches, and spans of a redaction, that one inner loop handles; loops of loops keep the work near-linear in their number.
CHUNK, REDACTED = 256, 64
#: Bins of p: steps of a tenth of a decade, so that the procedure needs a bounded table of counts.
BINS_A_DECADE, MOST_BIN = 10, 300
#: The alphabets in the order of their codes.
ALPHABETS = {
    "hex": "0123456789abcdef",
    "base32": "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567",
    "base64": "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/",
    "base64url": "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789-_",
}


def chunked(array: str, size: int) -> str:
    """SQL: an array cut into arrays of a given size."""
    return f"transform(sequence(0, (size({array}) - 1) DIV {size}), c -> slice({array}, 1 + c * {size}, {size}))"


def located(text: str, pattern: str, kind: int, value_group: int = 0) -> str:
    """SQL for the matches of a pattern as array<struct<start, kind, end, hit, value>>; group 1 is the gap before, group 2 the match.

    Offsets are sums of lengths, first by chunks of matches and then inside each, so that no long array is grown match by match.
    """
    full = rf"(?s)(.*?)({pattern}|\z)".replace("\\", "\\\\").replace("'", "\\'")
    quick = pattern.replace("\\", "\\\\").replace("'", "\\'")
    part = lambda g: f"regexp_extract_all({text}, '{full}', {g})"
    empty = "CAST(array() AS ARRAY<STRUCT<start: INT, kind: INT, end: INT, hit: STRING, value: STRING>>)"
    pieces = f"zip_with(zip_with({part(1)}, {part(2)}, (g, h) -> named_struct('gap', length(g), 'hit', h)), {part(2 + value_group)}, (y, v) -> named_struct('gap', y.gap, 'hit', y.hit, 'long', length(y.hit), 'value', v))"
    step = f"named_struct('start', acc.at + x.gap, 'kind', {kind}, 'end', acc.at + x.gap + x.long, 'hit', x.hit, 'value', x.value)"
    inside = f"aggregate(g, named_struct('at', s, 'out', {empty}), (acc, x) -> named_struct('at', acc.at + x.gap + x.long, 'out', CASE WHEN x.long > 0 THEN concat(acc.out, array({step})) ELSE acc.out END), acc -> acc.out)"
    sums = "transform(gs, g -> aggregate(g, 0, (n, x) -> n + x.gap + x.long))"
    starts = f"aggregate({sums}, named_struct('at', 0, 'out', CAST(array() AS ARRAY<INT>)), (acc, n) -> named_struct('at', acc.at + n, 'out', concat(acc.out, array(acc.at))), acc -> acc.out)"
    found = f"transform(array({pieces}), ps -> transform(array({chunked('ps', CHUNK)}), gs -> flatten(zip_with(gs, {starts}, (g, s) -> {inside})))[0])[0]"
    return f"CASE WHEN rlike({text}, '{quick}') THEN {found} ELSE {empty} END"


def normal_tail(z: str) -> str:
    """SQL for P(Z > z), by the usual rational approximation of the error function for z >= 0 (constants fixed)."""
    t = f"(1 / (1 + 0.3275911 * abs({z}) / sqrt(2)))"
    poly = f"{t} * (0.254829592 + {t} * (-0.284496736 + {t} * (1.421413741 + {t} * (-1.453152027 + {t} * 1.061405429))))"
    upper = f"(0.5 * ({poly}) * exp(-({z}) * ({z}) / 2))"
    return f"CASE WHEN {z} >= 0 THEN {upper} ELSE 1 - {upper} END"


def encoding(run: str) -> str:
    body = f"rtrim('=', {run})"
    mixed = f"rlike({body}, '[0-9]') AND rlike({body}, '[A-Z]') AND rlike({body}, '[a-z]')"
    return (
        f"CASE WHEN rlike({run}, '^([0-9a-f]+|[0-9A-F]+)$') AND rlike({run}, '[0-9]') AND rlike({run}, '[a-fA-F]') THEN 'hex' "
        f"WHEN rlike({run}, '^[A-Z2-7]+=*$') AND rlike({run}, '[2-7]') AND rlike({run}, '[A-Z]') THEN 'base32' "
        f"WHEN rlike({run}, '^[A-Za-z0-9+/]+=*$') AND {mixed} THEN 'base64' WHEN rlike({run}, '^[A-Za-z0-9_-]+=*$') AND {mixed} THEN 'base64url' END"
    )


def extended(df: DataFrame, column: str, fields: list[str], new: dict[str, str]) -> tuple[DataFrame, list[str]]:
    """Adds fields to the structs of an array column; ``new`` has SQL over x, the struct."""
    parts = [f"'{f}', x.{f}" for f in fields if f not in new] + [f"'{k}', {e}" for k, e in new.items()]
    return df.withColumn(column, F.expr(f"transform({column}, x -> named_struct({', '.join(parts)}))")), [*(f for f in fields if f not in new), *new]


def battery(df: DataFrame, column: str) -> DataFrame:
    """Tests every run of an array of spans; afterwards the spans have encoding, n, p_uniform, p_runs, p_serial, p, bin and band.

    Whole arrays are transformed step by step, so documents stay whole rows. The uniformity statistic is standardised by its exact
    mean and variance under random symbols, since short runs leave most cells of a large alphabet empty.
    """
    fields = ["start", "kind", "end", "hit"]
    alphabet = "CASE x.encoding " + " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in ALPHABETS.items()) + " END"
    symbols = "filter(split(CASE WHEN x.encoding = 'hex' THEN lower(x.hit) ELSE rtrim('=', x.hit) END, ''), c -> c <> '')"
    df, fields = extended(df, column, fields, {"encoding": encoding("x.hit")})
    df, fields = extended(df, column, fields, {"r": f"CAST(length({alphabet}) AS DOUBLE)", "v": f"transform({symbols}, c -> CAST(locate(c, {alphabet}) - 1 AS DOUBLE))"})
    df, fields = extended(df, column, fields, {"n": "CAST(size(x.v) AS DOUBLE)", "middle": "aggregate(x.v, 0D, (a, y) -> a + y) / size(x.v)", "squares": "aggregate(sequence(0, CAST(x.r AS INT) - 1), 0D, (a, k) -> a + pow(size(filter(x.v, y -> y = k)), 2))"})
    df, fields = extended(
        df,
        column,
        fields,
        {
            "above": "CAST(size(filter(x.v, y -> y >= x.r / 2)) AS DOUBLE)",
            "turns": "1D + size(filter(sequence(1, CAST(x.n AS INT) - 1), i -> (x.v[i] >= x.r / 2) <> (x.v[i - 1] >= x.r / 2)))",
            "spread": "aggregate(x.v, 0D, (a, y) -> a + pow(y - x.middle, 2))",
            "lagged": "aggregate(sequence(1, CAST(x.n AS INT) - 1), 0D, (a, i) -> a + (x.v[i] - x.middle) * (x.v[i - 1] - x.middle))",
        },
    )
    df, fields = extended(df, column, fields, {"mean_runs": "1 + 2 * x.above * (x.n - x.above) / x.n"})
    df, fields = extended(
        df,
        column,
        fields,
        {
            "z_uniform": "(x.squares * x.r / x.n - x.n - (x.r - 1)) / sqrt(2 * (x.r - 1) * (x.n - 1) / x.n)",
            "z_runs": "CASE WHEN x.above = 0 OR x.above = x.n THEN sqrt(x.n) ELSE abs(x.turns - x.mean_runs) / sqrt(greatest((x.mean_runs - 1) * (x.mean_runs - 2) / (x.n - 1), 1e-9D)) END",
            "z_serial": "CASE WHEN x.spread = 0 THEN sqrt(x.n) ELSE abs(x.lagged / x.spread + 1 / x.n) * sqrt(x.n) END",
        },
    )
    df, fields = extended(df, column, fields, {f"p_{k}": f"least(1D, {sides} * ({normal_tail(f'x.z_{k}')}))" for k, sides in (("uniform", 1), ("runs", 2), ("serial", 2))})
    df, fields = extended(df, column, fields, {"p": "greatest(1e-300D, 1D - pow(1D - least(x.p_uniform, x.p_runs, x.p_serial), 3))"})
    kept = ["start", "kind", "end", "hit", "encoding", "n", "p_uniform", "p_runs", "p_serial", "p"]
    return extended(df, column, kept, {"bin": f"CAST(least({MOST_BIN}, floor(-{BINS_A_DECADE} * log10(greatest(x.p, 1e-300D)))) AS INT)", "band": "CAST(floor(log2(x.n)) AS INT)"})[0]


def patterned(df: DataFrame, text_col: str) -> DataFrame:
    """Adds _base (spans of the patterns) and _runs (spans of the runs that no pattern touches)."""
    t = "_llm_text"
    df = df.withColumn(t, F.coalesce(F.col(f"`{text_col}`").cast("string"), F.lit("")))
    assign = f"filter({located(t, ASSIGN, 0, 2)}, x -> length(x.value) >= {MIN_VALUE})"
    df = df.withColumn("_base", F.expr(f"array_sort(concat({assign}, {located(t, ACCESS, 1)}, {located(t, HEX, 2)}))"))
    # the spans are bound once, and looked at by parts that may touch the run
    parts = f"transform({chunked('bs', REDACTED)}, g -> named_struct('low', array_min(transform(g, y -> y.start)), 'high', array_max(transform(g, y -> y.end)), 'g', g))"
    touched = "coalesce(exists(parts, p -> p.low < x.end AND x.start < p.high AND exists(p.g, y -> y.start < x.end AND x.start < y.end)), false)"
    runs = f"transform(array(_base), bs -> transform(array({parts}), parts -> filter({located(t, RUN, 3)}, x -> {encoding('x.hit')} IS NOT NULL AND NOT {touched}))[0])[0]"
    return df.withColumn("_runs", F.expr(runs))


def limit_of(counts: dict[int, int], fdr: float, report_fdr: float) -> int:
    """The bin of p from which runs of one band of lengths are not reported. counts: runs by bin."""
    total, below, rejected = sum(counts.values()), 0, MOST_BIN + 1
    for b in sorted(counts, reverse=True):
        below += counts[b]
        if 10 ** (-b / BINS_A_DECADE) <= below * fdr / total:
            rejected = b
    # random runs, from those with a large p; one more keeps small bands from none
    random = min(total, (1 + sum(n for b, n in counts.items() if b < SURE_BIN)) / (1 - 10 ** (-SURE_BIN / BINS_A_DECADE)))
    best, reported = 0, 0
    for b in range(1, rejected + 1):
        reported += counts.get(b - 1, 0)
        false = reported - random * (1 - 10 ** (-b / BINS_A_DECADE))
        if false <= report_fdr * reported:
            best = b
    return best


def thresholds(df: DataFrame, fdr: float, report_fdr: float = REPORT_FDR) -> dict[int, int]:
    """By band of lengths, the least bin of p that is not reported: from counts over the whole corpus, at most 301 a band."""
    counts: dict[int, dict[int, int]] = {}
    for r in df.select(F.explode("_runs").alias("s")).groupBy("s.band", "s.bin").agg(F.count("*").alias("k")).collect():
        counts.setdefault(r["band"], {})[r["bin"]] = r["k"]
    return {band: limit_of(bins, fdr, report_fdr) for band, bins in counts.items()}


def scan(docs: DataFrame, text_col: str = "text", fdr: float = FDR, keep: list[str] | None = None) -> DataFrame:
    """Adds secrets: array<struct<start, kind (index into KINDS), end>>, by start and kind. No shuffle of documents."""
    kept = [c for c in (docs.columns if keep is None else keep) if c.lower() != "secrets"]
    found = patterned(docs.select(*[F.col(f"`{c}`") for c in dict.fromkeys([*kept, text_col])]), text_col)
    found = battery(found, "_runs")
    limits = thresholds(found, fdr)
    limit = "CASE x.band " + " ".join(f"WHEN {a} THEN {b}" for a, b in sorted(limits.items())) + f" ELSE {MOST_BIN + 1} END" if limits else str(MOST_BIN + 1)
    spans = "transform({}, x -> named_struct('start', x.start, 'kind', x.kind, 'end', x.end))"
    return found.withColumn("secrets", F.expr(f"array_sort(concat({spans.format('_base')}, {spans.format(f'filter(_runs, x -> x.bin < {limit})')}))")).select(*[F.col(f"`{c}`") for c in kept], "secrets")


def redact(docs: DataFrame, text_col: str = "text", spans_col: str = "secrets", mark: str = "[SECRET]") -> DataFrame:
    """Replaces every span of the text by a mark; overlapping spans share one. Null texts stay null.

    Spans come in order of start. The text is cut once for every REDACTED of them, and then inside those parts.
    """
    t = f"`{text_col}`"
    far = "array_max(transform(g, x -> x.end))"
    froms = f"aggregate(gs, named_struct('at', 0, 'out', CAST(array() AS ARRAY<INT>)), (acc, g) -> named_struct('at', greatest(acc.at, {far}), 'out', concat(acc.out, array(acc.at))), acc -> acc.out)"
    piece = f"CASE WHEN x.start >= acc.at THEN concat(acc.out, substring(seg, acc.at - f + 1, x.start - acc.at), '{mark}') ELSE acc.out END"
    inside = f"transform(array(substring({t}, f + 1, greatest(f, {far}) - f)), seg -> aggregate(g, named_struct('at', f, 'out', ''), (acc, x) -> named_struct('at', greatest(acc.at, x.end), 'out', {piece}), acc -> acc.out))[0]"
    body = f"transform(array({chunked(spans_col, REDACTED)}), gs -> array_join(zip_with(gs, {froms}, (g, f) -> {inside}), ''))[0]"
    tail = f"substring({t}, 1 + array_max(transform({spans_col}, x -> x.end)))"
    return docs.withColumn(text_col, F.expr(f"CASE WHEN size({spans_col}) > 0 THEN concat({body}, {tail}) ELSE {t} END"))


def spelled(spans: str) -> str:
    """SQL: kind:start:end, joined by commas."""
    names = "array(" + ", ".join(f"'{k}'" for k in KINDS) + ")"
    return f"concat_ws(',', transform({spans}, x -> concat_ws(':', {names}[x.kind], CAST(x.start AS STRING), CAST(x.end AS STRING))))"


def op7_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan(load(spark, sf_dir, "documents"), keep=["doc_id"])
    counted = [F.expr(f"CAST(size(filter(secrets, x -> x.kind = {i})) AS BIGINT)").alias(f"n_{k}") for i, k in enumerate(KINDS[:3])]
    return found.select("doc_id", *counted, F.expr(f"sha2({spelled('filter(secrets, x -> x.kind < 3)')}, 256)").alias("base_sha256"), F.expr(spelled("secrets")).alias("spans"))
