"""Triples from files and columns: N-Triples text, JSON objects, HTML, tables; and sinks for links.

Triples are ``s, p, o, o_is_uri``.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

#: subject (URI or blank node), property, object (URI, literal or blank node); no step of it backtracks into a literal
LINE = r'^\s*(?:<([^>]*)>|(_:\S+))\s+<([^>]*)>\s+(?:<([^>]*)>|"([^"\\]*+(?:\\.[^"\\]*+)*+)"\S*|(_:\S+?))\s*\.\s*(?:#.*)?$'
#: The escapes of a literal, beside those by code point; the escape itself comes first.
ESCAPES = (("\\", "\\\\"), ('"', '\\"'), ("\n", "\\n"), ("\r", "\\r"), ("\t", "\\t"), ("\b", "\\b"), ("\f", "\\f"))
SAME_AS = "http://www.w3.org/2002/07/owl#sameAs"


def _points(text: Column, mark: str, digits: int) -> Column:
    """``text`` with the code points that escapes of ``mark`` and so many digits name."""
    cuts = F.split(text, rf"\\{mark}(?=[0-9A-Fa-f]{{{digits}}})")

    def after(cut: Column) -> Column:
        point = F.decode(F.unhex(F.lpad(F.substring(cut, 1, digits), 8, "0")), "UTF-32")
        return F.concat(point, F.substring(cut, digits + 1, 1 << 30))

    every = F.concat(F.get(cuts, F.lit(0)), F.array_join(F.transform(F.slice(cuts, 2, F.size(cuts)), after), ""))
    return F.when(F.contains(text, F.lit(f"\\{mark}")), every).otherwise(text)


def unescaped(text: Column) -> Column:
    """A literal's value. Between escaped escapes, every escape that is left stands for itself alone."""

    def plain(part: Column) -> Column:
        for value, escape in (*ESCAPES[1:], ("'", "\\'")):
            part = F.replace(part, F.lit(escape), F.lit(value))
        return _points(_points(part, "u", 4), "U", 8)

    whole = F.array_join(F.transform(F.split(text, r"\\\\"), plain), "\\")
    return F.when(F.contains(text, F.lit("\\")), whole).otherwise(text)


def parse_ntriples(line: Column) -> list[Column]:
    part = lambda i: F.regexp_extract(line, LINE, i)
    uri, blank = part(4), part(6)
    o = F.when(uri != "", uri).when(blank != "", blank).otherwise(unescaped(part(5)))
    return [F.concat(part(1), part(2)).alias("s"), part(3).alias("p"), o.alias("o"), ((uri != "") | (blank != "")).alias("o_is_uri")]


def read_ntriples(spark: SparkSession, path: str) -> DataFrame:
    """Triples of N-Triples files; comments and blank lines are skipped, other lines must parse."""
    lines = spark.read.text(path).where(~F.col("value").rlike(r"^\s*(#.*)?$"))
    checked = F.when(F.col("value").rlike(LINE), F.col("value")).otherwise(F.raise_error(F.concat(F.lit("no triple: "), "value")))
    return lines.select(checked.alias("value")).select(*parse_ntriples(F.col("value")))


def write_ntriples(triples: DataFrame, path: str) -> None:
    """One line per triple."""
    o = F.col("o")
    for plain, escaped in ESCAPES:
        o = F.replace(o, F.lit(plain), F.lit(escaped))
    node = lambda c: F.when(F.col(c).startswith("_:"), F.col(c)).otherwise(F.concat(F.lit("<"), c, F.lit(">")))
    shown = F.when(F.col("o_is_uri"), node("o")).otherwise(F.concat(F.lit('"'), o, F.lit('"')))
    triples.select(F.concat(node("s"), F.lit(" <"), "p", F.lit("> "), shown, F.lit(" .")).alias("value")).write.text(path)


def json_triples(df: DataFrame, id_col: str, json_col: str) -> DataFrame:
    """A triple per key of a flat JSON object; keys are found at run time."""
    rows = df.select(F.col(id_col).cast("string").alias("s"), F.explode(F.from_json(json_col, "map<string,string>")).alias("p", "o"))
    return rows.where("o is not null").withColumn("o_is_uri", F.lit(False))


def html_triples(pages: DataFrame, id_col: str = "page_id", html_col: str = "html") -> DataFrame:
    """Language, title, heading and every link target of a page."""
    single = {"lang": '<html lang="([^"]*)"', "title": "<title>([^<]*)</title>", "heading": "<h1>([^<]*)</h1>"}
    rows = [
        F.struct(F.lit(p).alias("p"), F.array(F.regexp_extract(html_col, pattern, 1)).alias("o"), F.lit(False).alias("u"))
        for p, pattern in single.items()
    ]
    links = F.regexp_extract_all(F.col(html_col), F.lit('href="([^"]*)"'), F.lit(1))
    rows.append(F.struct(F.lit("link").alias("p"), links.alias("o"), F.lit(True).alias("u")))
    out = pages.select(F.col(id_col).cast("string").alias("s"), F.explode(F.array(*rows)).alias("x"))
    out = out.select("s", "x.p", F.explode("x.o").alias("o"), F.col("x.u").alias("o_is_uri"))
    return out.where("o <> ''").distinct()


def table_triples(df: DataFrame, id_col: str, columns: list[str]) -> DataFrame:
    """A triple per non-null field of a table; narrow."""
    cells = F.array(*(F.struct(F.lit(c).alias("p"), F.col(c).cast("string").alias("o")) for c in columns))
    rows = df.select(F.col(id_col).cast("string").alias("s"), F.explode(cells).alias("x")).select("s", "x.p", "x.o")
    return rows.where("o is not null").withColumn("o_is_uri", F.lit(False))


def dereference(triples: DataFrame, labels: DataFrame | None = None) -> DataFrame:
    """URI objects by their names: ``labels`` (``uri, label``) where known, else the local name.

    The label table is joined without a hint: Spark broadcasts it if it is small.
    """
    local = F.regexp_extract("o", "([^/#:]*)$", 1)
    if labels is None:
        return triples.withColumn("o", F.when(F.col("o_is_uri"), local).otherwise(F.col("o")))
    rows = triples.join(labels, triples["o"] == labels["uri"], "left")
    named = F.when(F.col("o_is_uri"), F.coalesce("label", local)).otherwise(F.col("o"))
    return rows.select("s", "p", named.alias("o"), "o_is_uri")


def match(triples: DataFrame, s: str | None = None, p: str | None = None, o: str | None = None) -> DataFrame:
    """Triples of a pattern; filters reach the scan, and prune it if it is partitioned by ``p``."""
    for name, value in (("s", s), ("p", p), ("o", o)):
        if value is not None:
            triples = triples.where(F.col(name) == value)
    return triples


def upsert(triples: DataFrame, added: DataFrame, removed: DataFrame | None = None) -> DataFrame:
    """The graph after an update."""
    if removed is not None:
        triples = triples.join(removed.select("s", "p", "o"), ["s", "p", "o"], "left_anti")
    return triples.unionByName(added).distinct()


def emit_links(pairs: DataFrame, predicate: str = SAME_AS) -> DataFrame:
    """An equality edge per pair."""
    return pairs.select(F.col("l_rid").alias("s"), F.lit(predicate).alias("p"), F.col("r_rid").alias("o"), F.lit(True).alias("o_is_uri"))


def write_index(index: DataFrame, path: str) -> None:
    """Keep an inverted index: Parquet by term, sorted by key within files, so that a later join prunes."""
    index.repartition("term_id", "key").sortWithinPartitions("term_id", "key").write.partitionBy("term_id").parquet(path)


def save_index(index: DataFrame, table: str, buckets: int = 512, mode: str = "error") -> DataFrame:
    """Keep an inverted index as a table bucketed and sorted by term and key.

    Two of them with as many buckets meet on their keys without a shuffle; ``mode="append"`` adds records to one.
    """
    rows = index.repartition(buckets, "term_id", "key")
    rows.write.bucketBy(buckets, "term_id", "key").sortBy("term_id", "key").mode(mode).format("parquet").saveAsTable(table)
    return index.sparkSession.table(table)


class NTriplesSource(DataSource):
    """``spark.read.format("ntriples").load(path)`` over a file or folder of any file system that Arrow reads.

    Files are read in parts of ``part_bytes`` (64 MiB by default): a line belongs to the part that it begins in.
    """

    @classmethod
    def name(cls) -> str:
        return "ntriples"

    def schema(self) -> str:
        return "s string, p string, o string, o_is_uri boolean"

    def reader(self, schema) -> DataSourceReader:
        return _NTriplesReader(self.options["path"], int(self.options.get("part_bytes", 64 << 20)))


@dataclass
class _Part(InputPartition):
    path: str
    start: int
    end: int


class _NTriplesReader(DataSourceReader):
    def __init__(self, path: str, part_bytes: int):
        self.path, self.part_bytes = path, part_bytes

    def _files(self):
        from pyarrow import fs

        return fs.FileSystem.from_uri(self.path if "://" in self.path else f"file://{self.path.removeprefix('file:')}")

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs

        system, root = self._files()
        found = system.get_file_info(root)
        if found.type == fs.FileType.NotFound:
            raise FileNotFoundError(self.path)
        if found.type == fs.FileType.Directory:
            found = system.get_file_info(fs.FileSelector(root, recursive=True))
        files = [f for f in (found if isinstance(found, list) else [found]) if f.is_file and f.base_name[0] not in "._"]
        return [_Part(f.path, at, min(at + self.part_bytes, f.size)) for f in files for at in range(0, f.size, self.part_bytes)]

    def read(self, partition: _Part) -> Iterator[tuple]:
        import re

        line_of = re.compile(LINE)
        with self._files()[0].open_input_file(partition.path) as file:
            for line in _lines(file, partition.start, partition.end):
                if line.strip() and not line.lstrip().startswith("#"):
                    m = line_of.match(line)
                    if not m:
                        raise ValueError(f"no triple: {line!r}")
                    uri, text, blank = m[4], m[5], m[6]
                    o = uri if uri is not None else blank if blank is not None else _value(text)
                    yield m[1] if m[1] is not None else m[2], m[3], o, text is None


def _lines(file, start: int, end: int, step: int = 1 << 20) -> Iterator[str]:
    """The lines of a file that begin from ``start`` up to before ``end``."""
    at = max(start - 1, 0)  # the byte before tells whether a line begins at ``start``
    file.seek(at)
    held, skip = b"", start > 0
    while True:
        part = file.read(step)
        held += part
        lines = held.split(b"\n")
        held = lines.pop()
        for line in lines:
            if skip:
                skip = False
            elif at < end:
                yield line.decode().rstrip("\r")
            else:
                return
            at += len(line) + 1
        if not part:
            if held and not skip and at < end:
                yield held.decode()
            return


def _value(text: str) -> str:
    """A literal's value, of its escaped form."""
    import re

    known = {escape[1]: value for value, escape in ESCAPES} | {"'": "'"}
    return re.sub(
        r"\\(?:u([0-9A-Fa-f]{4})|U([0-9A-Fa-f]{8})|(.))",
        lambda m: chr(int(m[1] or m[2], 16)) if m[1] or m[2] else known.get(m[3], m[0]),
        text,
    )
