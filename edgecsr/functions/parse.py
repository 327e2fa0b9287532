"""Number parsers for edge lines: expressions for whole columns, and bulk parsing of buffers.

All of them end at the line end, accept blanks, tabs, commas and semicolons as
separators, and skip blank lines and lines that begin with % or #. One grammar
holds for all: an id is an optional sign and digits that fit 64 bits, a weight
is a decimal number with an optional sign and exponent; what follows the third
token does not count. (``digit_scan`` takes the numbers out of any line, by its nature.)
"""

from __future__ import annotations

import io
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.csv as pacsv
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PARSERS = ("generic", "format", "direct", "vector", "digit_scan")
_NUMBER = r"[+-]?[0-9]*\.?[0-9]+(?:[eE][+-]?[0-9]+)?"
#: White space that may stand at both ends of a line.
BLANKS = b" \t\r\n\x0b\x0c"
_ID = re.compile(rb"[+-]?[0-9]+\Z")
_WEIGHT = re.compile(rb"[+-]?(?:[0-9]+\.?[0-9]*|\.[0-9]+)(?:[eE][+-]?[0-9]+)?\Z")
_SEPARATED = bytes.maketrans(b"\t,;\r\x0b\x0c", b"      ")
#: Bytes of regular blocks; any other sends a block through the line-by-line parse.
_REGULAR = b"0123456789+-.eE \t,\n"
#: Blank lines and comments.
_NO_DATA = r"^\s*([%#]|$)"
#: Lines whose tokens need no more care: ids and a plain weight, one blank between them.
_PLAIN = r"^[0-9]{1,18}+ [0-9]{1,18}+(?: [0-9]{1,15}+(?:\.[0-9]{0,15}+)?+)?+\z"


def whole_number(c: Column, plain: Column | None = None) -> Column:
    """Signed 64-bit number, null where the token is none or does not fit; ``plain`` tells tokens that are digits."""
    own = ~c.rlike("[^0-9+-]")
    return F.when(own if plain is None else plain | own, c.try_cast("long"))


def decimal_number(c: Column, plain: Column | None = None) -> Column:
    """Parsed as double, then rounded to single precision; no names of numbers, no suffixes."""
    own = ~c.rlike("[^0-9+.eE-]")
    return F.when(own if plain is None else plain | own, c.try_cast("double").cast("float"))


def _cleaned(value: Column) -> Column:
    return F.trim(F.translate(value, "\t,;\r\x0b\x0c", "      "))


def _once(df: DataFrame, name: str, value: Column) -> DataFrame:
    """Adds a computed column that is evaluated once a row: filters are not pushed through a generator, which would repeat ``value`` for every use of it."""
    return df.select("*", F.explode(F.array(value)).alias(name))


def _tokens(df: DataFrame, parser: str) -> tuple[DataFrame, list[Column]]:
    """Adds the tokens of a line as _t, and tells its first three, null where missing; _plain lines are taken as they are."""
    line = lambda other: F.when(F.col("_plain"), F.col("value")).otherwise(other)
    squeezed = F.regexp_replace(_cleaned(F.col("value")), " +", " ")
    if parser == "direct":
        found = F.split(line(squeezed), " ")
    elif parser == "generic":
        found = F.regexp_extract_all(line(_cleaned(F.col("value"))), F.lit(r"(\S++)"), 1)
    elif parser == "format":
        parsed = F.from_csv(line(squeezed), "a string, b string, w string", {"sep": " ", "mode": "PERMISSIVE", "quote": "", "escape": "", "inputBufferSize": "1024"})
        return _once(df, "_t", parsed), [F.col(f"_t.{n}") for n in "abw"]
    elif parser == "digit_scan":  # any other characters separate numbers
        found = F.regexp_extract_all("value", F.lit(f"({_NUMBER})"), 1)
    else:
        raise ValueError(f"parser must be one of {PARSERS}")
    return _once(df, "_t", found), [F.get("_t", F.lit(i)) for i in range(3)]


def data_lines(lines: DataFrame) -> DataFrame:
    """Lines that are neither blank nor comments."""
    return lines.where(~F.col("value").rlike(_NO_DATA))


def parse_lines(lines: DataFrame, parser: str = "direct", weighted: bool = True, base: int = 1, mode: str = "PERMISSIVE") -> tuple[DataFrame, DataFrame]:
    """(edges, bad records) of a ``value`` column; further columns are kept with the edges.

    PERMISSIVE and DROPMALFORMED leave bad lines out of the edges (the second
    result tells them), FAILFAST fails on the first.
    """
    rest = [c for c in lines.columns if c != "value"]
    if parser == "vector":
        return _parse_vector(lines, weighted, base, mode), _bad_vector(lines, weighted, base)
    plain = F.col("_plain")
    told = _once(lines, "_plain", F.col("value").rlike(_PLAIN))
    cut, (a, b, w) = _tokens(told.where(plain | ~F.col("value").rlike(_NO_DATA)), parser)
    weight = F.when(w.isNull(), F.lit(1.0).cast("float")).otherwise(decimal_number(w, plain)) if weighted else F.lit(1.0).cast("float")
    numbers = F.struct(whole_number(a, plain).alias("src"), whole_number(b, plain).alias("dst"), weight.alias("weight"), b.isNull().alias("_short"))
    parsed = _once(cut, "_n", numbers).select(*rest, "value", "_n.*")
    reason = (
        F.when(F.col("_short"), "missing target")
        .when(F.col("src").isNull() | F.col("dst").isNull(), "bad id")
        .when((F.col("src") < base) | (F.col("dst") < base), "below index base")
        .when(F.col("weight").isNull(), "bad weight")
    )
    told = parsed.withColumn("reason", reason)
    bad = told.where(F.col("reason").isNotNull()).select(F.col("value").alias("line"), "reason")
    if mode == "FAILFAST":
        told = told.withColumn("src", F.when(F.col("reason").isNotNull(), F.raise_error(F.concat(F.lit("bad edge line: "), F.col("value"))).cast("long")).otherwise(F.col("src")))
    good = told.where(F.col("reason").isNull()) if mode != "FAILFAST" else told
    return good.select((F.col("src") - base).alias("src"), (F.col("dst") - base).alias("dst"), "weight", *rest), bad


def parse_line(line: bytes, weighted: bool = True, base: int = 1) -> tuple[tuple[int, int, float] | None, str | None]:
    """The edge of one line, or the reason why it is bad; neither for a blank line or a comment."""
    parts = line.translate(_SEPARATED).split()
    bare = line.strip(BLANKS)
    if not bare or bare[:1] in b"%#":
        return None, None
    if len(parts) < 2:
        return None, "missing target"
    a, b = parts[:2]
    if not (_ID.match(a) and _ID.match(b)) or max(len(a), len(b)) > 400:
        return None, "bad id"
    a, b, w = int(a), int(b), 1.0
    if not (-(2**63) <= a < 2**63 and -(2**63) <= b < 2**63):
        return None, "bad id"
    if a < base or b < base:
        return None, "below index base"
    if weighted and len(parts) > 2:
        if not _WEIGHT.match(parts[2]):
            return None, "bad weight"
        w = float(parts[2])
    return (a - base, b - base, w), None


def parse_buffer(data: bytes, weighted: bool = True, base: int = 1, bad: list[tuple[str, str]] | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Whole lines in bulk: by Arrow's csv reader if the block is regular, else line by line.

    Bad lines are left out; ``bad`` takes each with its reason.
    """
    if not data or data.isspace():
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.float32)
    names, kinds = (["a", "b", "w"], {"a": pa.int64(), "b": pa.int64(), "w": pa.float64()}) if weighted else (["a", "b"], {"a": pa.int64(), "b": pa.int64()})
    sep = b"\t" if b"\t" in data[:4096] else b"," if b"," in data[:4096] else b" "
    try:
        if data.translate(None, _REGULAR):
            raise pa.ArrowInvalid("other characters")
        t = pacsv.read_csv(io.BytesIO(data), pacsv.ReadOptions(column_names=names, use_threads=False), pacsv.ParseOptions(delimiter=sep.decode()), pacsv.ConvertOptions(column_types=kinds))
        if any(c.null_count for c in t.columns):
            raise pa.ArrowInvalid("missing values")
        a, b = t.column("a").to_numpy(), t.column("b").to_numpy()
        w = t.column("w").to_numpy().astype(np.float32) if weighted else np.ones(len(a), np.float32)
        fine = (a >= base) & (b >= base)
        if fine.all() or bad is None:
            return a[fine] - base, b[fine] - base, w[fine]
    except pa.ArrowInvalid:
        pass
    rows = []
    for line in data.split(b"\n"):
        found, reason = parse_line(line, weighted, base)
        if found:
            rows.append(found)
        elif reason and bad is not None:
            bad.append((line.decode("utf-8", "replace"), reason))
    with np.errstate(over="ignore"):
        a, b, w = (np.array([r[i] for r in rows], t) for i, t in enumerate((np.int64, np.int64, np.float32)))
    return a, b, w


def _text(values: pa.Array) -> bytes:
    """The lines of a column as one text, without an object for each."""
    values = values.drop_null().cast(pa.string())
    return pc.binary_join(pa.ListArray.from_arrays(pa.array([0, len(values)], pa.int32()), values), "\n")[0].as_buffer().to_pybytes()


def _bad_vector(lines: DataFrame, weighted: bool, base: int) -> DataFrame:
    """Bad records of the bulk parse: computed only if they are asked for."""

    def run(found: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in found:
            bad: list[tuple[str, str]] = []
            parse_buffer(_text(batch.column(0)), weighted, base, bad)
            if bad:
                yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in bad], pa.string()) for i in (0, 1)], ["line", "reason"])

    return lines.select("value").mapInArrow(run, "line string, reason string")


def _parse_vector(lines: DataFrame, weighted: bool, base: int, mode: str = "PERMISSIVE") -> DataFrame:
    """Bulk parse of Arrow batches of lines; further columns must be integers and are kept."""
    rest = [c for c in lines.columns if c != "value"]
    kinds = ", ".join(f"{c} {lines.schema[c].dataType.simpleString()}" for c in rest)

    def run(found: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in found:
            if not batch.num_rows:
                continue
            keys = [tuple(c[0].as_py() for c in batch.columns[1:])] if rest else [()]
            same = all(pc.count_distinct(c).as_py() == 1 for c in batch.columns[1:])
            groups = [(keys[0], _text(batch.column(0)))] if same else []
            if not same:
                by: dict[tuple, list] = {}
                for value, *key in zip(*[c.to_pylist() for c in batch.columns]):
                    by.setdefault(tuple(key), []).append(value)
                groups = [(key, "\n".join([v for v in values if v is not None]).encode()) for key, values in by.items()]
            for key, text in groups:
                bad: list[tuple[str, str]] | None = [] if mode == "FAILFAST" else None
                src, dst, w = parse_buffer(text, weighted, base, bad)
                if bad:
                    raise ValueError(f"bad edge line: {bad[0][0]}")
                more = [pa.array(np.full(len(src), k), batch.schema.field(i + 1).type) for i, k in enumerate(key)]
                yield pa.RecordBatch.from_arrays([pa.array(src), pa.array(dst), pa.array(w, pa.float32()), *more], ["src", "dst", "weight", *rest])

    return lines.select("value", *rest).mapInArrow(run, "src long, dst long, weight float" + (", " + kinds if rest else ""))
