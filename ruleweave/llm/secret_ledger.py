"""Secret scans with an incremental blob ledger (op9), in DataFrame functions only.

Every version of a text is a blob, named by the SHA-256 of its content. The ledger remembers which blobs each
version of each rule has seen; a scan reads one path of each blob for which a pair of blob and rule version is
missing, and findings are joined back to all paths that hold the blob, old and new. A blob that a third of
all paths share is scanned once, and the join back is salted so that its paths spread over tasks.

Positions come from splitting a text at a rule's matches: the gaps' and matches' lengths, summed up in a
window, give each match's start and end in code points.

Null texts count as empty (no findings). Repeated rows are paths of the same blob. A null doc_id is a path of its own.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ruleweave.llm.common import shared_dir

SALTS = 16
# The ledger's two tables.
TABLES = {"scanned": "blob string, kind string, version int", "findings": "blob string, kind string, start long, end long, version int"}
MASK = "[secret]"


@dataclass(frozen=True)
class Rule:
    """A pattern; a match counts if its group has `least` characters. A rule that changes gets a new version."""

    kind: str
    pattern: str
    group: int = 0
    least: int = 1
    version: int = 1


# The three base rules, then the rules that the method adds. The second and third demand their least length in
# the pattern itself, which finds the same runs as dropping short ones afterwards.
BASE = (
    Rule("assign", r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    Rule("access", r"AKIA[A-Z0-9]{16,}"),
    Rule("hex", r"[0-9a-f]{24,}"),
)
# A private key goes to its END line, whatever stands before that except another such line. Where the line is missing, it goes to the end
# of its base64 runs, after lines like "DEK-Info: ..."; line ends may be escaped. Runs are of 16 characters or more, but for the last.
_GAP = r"(?:[\s>|\"'+,#*]|\\[nrt])"
_PRIVATE_KEY = (
    r"-----BEGIN [A-Z0-9 ]{0,40}PRIVATE KEY(?: BLOCK)?-----"
    r"(?:[^-]*+(?:-(?!----)[^-]*+){0,200}+-----END [A-Z0-9 ]{0,40}PRIVATE KEY(?: BLOCK)?-----"
    rf"|(?:{_GAP}{{1,40}}+[A-Z][A-Za-z-]{{2,30}}:\x20[^\s\\]++(?:\x20[^\s\\:]++(?=[\s\\])){{0,3}}?(?=[\r\n\\])){{0,8}}+"
    rf"(?:{_GAP}{{0,40}}+[A-Za-z0-9+/]{{16,}}+={{0,2}}+){{1,4000}}+(?:{_GAP}{{1,40}}+[A-Za-z0-9+/]{{1,15}}+={{0,2}}+(?![A-Za-z0-9_:.-]))?+)?+"
)
ADDED = (
    Rule("private_key", _PRIVATE_KEY, version=2),
    Rule("web_token", r"eyJ[A-Za-z0-9_-]{10,}\.eyJ[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}"),
    Rule("forge_token", r"gh[pousr]_[A-Za-z0-9]{36,}"),
)
RULES = BASE + ADDED


def _sql_text(pattern: str) -> Column:
    return F.lit(pattern)


def _matches(text: Column, rule: Rule, number: int) -> Column:
    """Array of (number, gap length, match length, kept) of one rule, empty where the rule does not match at all."""
    p = _sql_text(rule.pattern)
    hits, groups = F.regexp_extract_all(text, p, F.lit(0)), F.regexp_extract_all(text, p, F.lit(rule.group))
    sized = F.zip_with(hits, groups, lambda h, g: F.struct(F.length(h).alias("size"), (F.length(g) >= rule.least).alias("kept")))
    rows = F.zip_with(F.split(text, rule.pattern, -1), sized, lambda gap, m: F.struct(F.lit(number).alias("rule"), F.length(gap).alias("gap"), m["size"].alias("size"), m["kept"].alias("kept")))
    return F.when(F.regexp_like(text, p), rows).otherwise(F.array().cast("array<struct<rule:int,gap:int,size:int,kept:boolean>>"))


def spans(blobs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """blob, rule (kind), start, end of every kept match in the column text of blobs (blob, text, todo: the rules to apply)."""
    text = F.col("text")
    found = blobs.withColumn("rw_row", F.monotonically_increasing_id())  # before the matches become rows of their own
    found = found.select("blob", "rw_row", F.posexplode(F.concat(*[F.when(F.array_contains("todo", r.kind), _matches(text, r, k)).otherwise(F.array().cast("array<struct<rule:int,gap:int,size:int,kept:boolean>>")) for k, r in enumerate(rules)])).alias("at", "m"))
    found = found.select("blob", "rw_row", "at", "m.*").filter(F.col("size").isNotNull())
    upto = Window.partitionBy("rw_row", "rule").orderBy("at").rowsBetween(Window.unboundedPreceding, 0)
    found = found.withColumn("end", F.sum(F.col("gap") + F.col("size")).over(upto)).filter("kept")
    kinds = F.array(*[F.lit(r.kind) for r in rules])
    return found.select("blob", kinds[F.col("rule")].alias("kind"), (F.col("end") - F.col("size")).alias("start"), "end").distinct()


class Ledger:
    """A ledger in a folder: scanned (blob, kind, version) and findings (blob, kind, version, start, end), both append-only Parquet."""

    def __init__(self, spark: SparkSession, folder: str | None = None, rules: tuple[Rule, ...] = RULES):
        self.spark, self.rules = spark, rules
        self.folder = folder or shared_dir(spark)

    def _read(self, name: str) -> DataFrame:
        """A table of the ledger, empty as long as nothing was written."""
        try:
            return self.spark.read.schema(TABLES[name]).parquet(f"{self.folder}/{name}")
        except AnalysisException as problem:
            if problem.getCondition() != "PATH_NOT_FOUND":
                raise
            return self.spark.createDataFrame([], TABLES[name])

    def _versions(self) -> Column:
        return F.create_map(*[F.lit(x) for r in self.rules for x in (r.kind, r.version)])

    def scan(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> Ledger:
        """Scans what no earlier call has: blobs of docs that a rule, in its present version, has not seen."""
        paths = _paths(docs, id_col, text_col)
        wanted = paths.groupBy("blob").agg(F.min("rw_key").alias("rw_key"))
        everything = F.array(*[F.lit(r.kind) for r in self.rules])
        scanned = self._read("scanned").filter(F.col("version") == self._versions()[F.col("kind")])
        if scanned.isEmpty():
            todo = wanted.withColumn("todo", everything)
        else:
            current = scanned.groupBy("blob").agg(F.collect_set("kind").alias("seen"))  # at most a kind a rule
            todo = wanted.join(current, "blob", "left").select("blob", "rw_key", F.array_except(everything, F.coalesce("seen", F.array().cast("array<string>"))).alias("todo")).filter(F.size("todo") > 0)
        texts = docs.select(_key(F.col(id_col)).alias("rw_key"), F.coalesce(text_col, F.lit("")).alias("text"))
        blobs = texts.join(todo, "rw_key").filter(F.col("blob") == F.sha2("text", 256))
        version = self._versions()
        spans(blobs, self.rules).withColumn("version", version[F.col("kind")]).write.mode("append").parquet(f"{self.folder}/findings")
        todo.select("blob", F.explode("todo").alias("kind")).withColumn("version", version[F.col("kind")]).write.mode("append").parquet(f"{self.folder}/scanned")
        return self

    def findings(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
        """One row a path: doc_id, blob, and found: its spans (start, rule number, kind, end) in order, empty if there are none or nothing
        was scanned yet."""
        numbers = F.create_map(*[F.lit(x) for k, r in enumerate(self.rules) for x in (r.kind, k)])
        current = self._read("findings").filter(F.col("version") == self._versions()[F.col("kind")]).dropDuplicates(["blob", "kind", "start", "end"])
        of_blob = current.groupBy("blob").agg(F.array_sort(F.collect_list(F.struct("start", numbers[F.col("kind")].alias("number"), "kind", "end"))).alias("found"))
        of_blob = of_blob.withColumn("rw_salt", F.explode(F.array(*[F.lit(k) for k in range(SALTS)])))
        paths = _paths(docs, id_col, text_col).withColumn("rw_salt", F.pmod(F.xxhash64("doc_id"), F.lit(SALTS)).cast("int"))
        return paths.join(of_blob, ["blob", "rw_salt"], "left").select("doc_id", "blob", F.coalesce("found", F.array().cast("array<struct<start:bigint,number:int,kind:string,end:bigint>>")).alias("found"))


def _key(doc_id: Column) -> Column:
    return F.coalesce(doc_id.cast("long"), F.lit(-(1 << 63)))


def _paths(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), _key(F.col(id_col)).alias("rw_key"), F.sha2(F.coalesce(text_col, F.lit("")), 256).alias("blob"))


def digest(findings: DataFrame) -> DataFrame:
    """doc_id, counts of the base kinds, base_sha256 (of kind:start:end, comma-joined) and spans (all of them, joined likewise)."""
    joined = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    count = lambda kind: F.size(F.filter("found", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    base = F.filter("found", lambda s: s["number"] < len(BASE))
    return findings.select("doc_id", *[count(r.kind) for r in BASE], F.sha2(joined(base), 256).alias("base_sha256"), joined(F.col("found")).alias("spans"))


def masked(text: Column, rules: tuple[Rule, ...] = RULES) -> Column:
    """The text with every kept match of the rules, one after the other, replaced by MASK."""
    for rule in sorted(rules, key=lambda r: r.kind != "private_key"):  # whole keys before others match inside them
        # named once, as the only element of an array, so that a rule's result is not computed anew wherever the next one uses it
        text = F.get(F.transform(F.array(text), _masker(rule)), 0)
    return text


def _masker(rule: Rule):
    return lambda t: _masked_by(t, rule)


def _masked_by(text: Column, rule: Rule) -> Column:
    p = _sql_text(rule.pattern)
    hits = F.zip_with(F.regexp_extract_all(text, p, F.lit(0)), F.regexp_extract_all(text, p, F.lit(rule.group)), lambda h, g: F.when(F.length(g) >= rule.least, MASK).otherwise(h))
    return F.array_join(F.zip_with(F.split(text, rule.pattern, -1), hits, lambda gap, h: F.concat(gap, F.coalesce(h, F.lit("")))), "")
