"""Operator 4: line deduplication by a log-template tree (DataFrame functions only).

A document is read as a log: its records are lines, cut further where sentences end.
A record is parsed at fixed depth: its number of tokens, then its leading tokens, lead to
a leaf; tokens with digits are variable fields from the start.  Inside a leaf that several
documents reach, a token that few of them have at its place is a variable field too.  What
is left, constants with ``<*>`` between them, is the template of the record; templates of
enough documents recur, and all their records but the first are dropped.  Two documents
are enough where repeated records follow each other to a passage of some length.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import join_unique, settle_table

FIELD = "<*>"
#: Records end behind a line feed, and behind a full stop and a space.
ENDS = ("\n", ". ", "! ", "? ")
#: Set behind each end; a text that has it itself is cut by pattern, which is slower.
CUT = "\x01"
RECORD_END = r"(?<=\n|[.!?] )"
#: Leaves worth a second look are marked in so many slots, which bounds what is broadcast.
SLOTS = 1 << 20


@dataclass(frozen=True)
class Rules:
    """When a template recurs.

    depth: leading tokens that choose the leaf.  min_tokens: shorter records never recur by
    themselves, unless they are whole lines of min_line_tokens in min_line_docs documents.
    min_docs: documents (of different texts) that must share a template.  constant: least
    share of constant tokens in a template with variable fields.

    passage_tokens: repeated records that follow each other, at most ``gap`` places apart, are
    a passage from so many tokens on; two documents are enough for it to recur, and the short
    records inside it go with it.  near_copy: a document that holds less than this share besides is a near
    copy as a whole, and what only two documents share stays in it (near-dedup compares whole texts).
    """

    depth: int = 4
    min_tokens: int = 8
    min_docs: int = 3
    constant: float = 0.75
    min_line_tokens: int = 3
    min_line_docs: int = 20
    passage_tokens: int = 50
    gap: int = 3
    near_copy: float = 0.15


def _marked(text: Column) -> Column:
    for end in ENDS:
        text = F.replace(text, F.lit(end), F.lit(end + CUT))
    return text


def record_list(text: Column) -> Column:
    """The records of a text; joined they give the text back."""
    return F.when(F.contains(text, F.lit(CUT)), F.split(text, RECORD_END)).otherwise(F.split(_marked(text), CUT))


def record_count(text: Column) -> Column:
    """The number of records without cutting them out."""
    return F.when(F.contains(text, F.lit(CUT)), F.size(F.split(text, RECORD_END))).otherwise(F.octet_length(_marked(text)) - F.octet_length(text) + 1)


def masked(record: Column) -> Column:
    """A record with its tokens that have a digit as variable fields, without trailing white space."""
    return F.when(record.rlike("[0-9]"), F.regexp_replace(record, r"[^ \n]*[0-9][^ \n]*", FIELD)).otherwise(record)


def _records(docs: DataFrame, id_col: str, text_col: str, rules: Rules) -> DataFrame:
    """(id, th, own, i, line, n, leaf, tpl, shape): a row for each record long enough to recur; own: tokens of its text.

    The number of tokens, the leaf and the template are found on the string; no record is
    cut into tokens here.
    """
    own = F.octet_length(text_col) - F.octet_length(F.replace(F.replace(F.col(text_col), F.lit(" "), F.lit("")), F.lit("\n"), F.lit(""))) + 1
    texts = docs.select(F.col(id_col).alias("id"), F.xxhash64(text_col).alias("th"), own.alias("own"), F.col(text_col).alias("text"))

    def shaped(record: Column) -> Column:
        shape = F.when(F.octet_length(record) > 2 * rules.min_line_tokens, F.rtrim(masked(record), F.lit(" \n")))
        return F.struct(record.endswith("\n").alias("line"), shape.alias("shape"))

    def counted(r: Column) -> Column:
        n = F.octet_length(r["shape"]) - F.octet_length(F.replace(r["shape"], F.lit(" "), F.lit(""))) + 1
        return F.struct(r["line"].alias("line"), r["shape"].alias("shape"), n.alias("n"))

    # Inside the generator each record is masked once; as columns above it, the filter on n would mask it again for each use.
    each = texts.select("id", "th", "own", F.posexplode(F.transform(F.transform(record_list(F.col("text")), shaped), counted)).alias("i", "r"))
    each = each.select("id", "th", "own", "i", "r.line", "r.n", "r.shape").filter((F.col("n") >= rules.min_tokens) | (F.col("line") & (F.col("n") >= rules.min_line_tokens)))
    return each.select("id", "th", "own", "i", "line", "n", F.xxhash64("n", F.substring_index("shape", " ", rules.depth)).alias("leaf"), F.xxhash64("shape").alias("tpl"), "shape")


def _texts(df: DataFrame, keys: list[str], *more: Column) -> DataFrame:
    """Number of different texts for each key, in two steps so that a common key stays small."""
    once = df.groupBy(*keys, "th").agg(*(more or [F.lit(1).alias("one")]))
    return once.groupBy(*keys).agg(F.count(F.lit(1)).alias("texts"), *(F.max(c).alias(c) for c in once.columns if c not in {*keys, "th", "one"}))


def recurring(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules: Rules = Rules()) -> DataFrame:
    """(id, th, flags): what ``drop_recurring`` takes from each document that has repeated records, by place.

    1: the record goes.  2: it lies inside a long passage that goes, and goes too if it is short.  0 and
    places beyond the end: it stays.
    """
    # The shapes are kept beside the hashes, so that a second look need not parse the texts again.
    thin = settle_table(_records(docs, id_col, text_col, rules).withColumn("shape", F.when(F.col("n") >= rules.min_tokens, F.col("shape"))))

    # Templates whose records are equal but for fields with digits.
    equal = settle_table(_texts(thin, ["tpl"], F.max("leaf").alias("leaf"), F.max("line").alias("line"), F.max("n").alias("n")).filter("texts > 1 or n >= %d" % rules.min_tokens))
    long = F.col("n") >= rules.min_tokens
    recurs = (long & (F.col("texts") >= rules.min_docs)) | (F.col("line") & (F.col("texts") >= rules.min_line_docs))
    plain = equal.filter(recurs).select("tpl", F.col("tpl").alias("template"))

    # Leaves that enough documents reach by records that are no templates yet.
    rest = equal.filter(long & ~recurs)
    leaves = settle_table(rest.groupBy("leaf").agg(F.sum("texts").alias("reach"), F.count(F.lit(1)).alias("kinds")).filter((F.col("reach") >= rules.min_docs) & (F.col("kinds") > 1)).select("leaf"))
    open_tpls = rest.join(leaves, "leaf", "left_semi").select("tpl")
    loose = _fielded(thin, leaves, open_tpls, rules)

    pairs = equal.filter(long & ~recurs & (F.col("texts") > 1)).select("tpl").join(loose.select("tpl"), "tpl", "left_anti").select("tpl", F.col("tpl").alias("template"))
    named = settle_table(plain.unionByName(loose).withColumn("weak", F.lit(False)).unionByName(pairs.withColumn("weak", F.lit(True))))
    hits = settle_table(join_unique(thin.select("id", "th", "own", "i", "n", "tpl"), named, ["tpl"], ["id", "i"]).drop("tpl"))
    first = hits.groupBy("template").agg(F.min(F.struct("id", "i")).alias("first"))
    behind = join_unique(hits, first, ["template"], ["id", "i"])
    behind = behind.filter(~(F.col("first.id").eqNullSafe(F.col("id")) & (F.col("first.i") == F.col("i"))))
    return _passages(behind.groupBy("id", "th", "i").agg(F.max("n").alias("n"), F.max("own").alias("own"), F.min("weak").alias("weak")), rules)


def _passages(behind: DataFrame, rules: Rules) -> DataFrame:
    """Repeated records (id, th, i, n, own, weak) as passages of neighbours, and the flags of each document."""
    text = Window.partitionBy("id", "th")
    begins = F.coalesce((F.col("i") - F.lag("i").over(text.orderBy("i")) > rules.gap).cast("int"), F.lit(1))
    runs = behind.withColumn("begins", begins).withColumn("run", F.sum("begins").over(text.orderBy("i")))
    run = Window.partitionBy("id", "th", "run")
    runs = runs.withColumns({"words": F.sum("n").over(run), "some_weak": F.max("weak").over(run), "all": F.sum("n").over(text)})
    carrier = F.col("all") <= (1 - rules.near_copy) * F.col("own")
    long = F.col("words") >= rules.passage_tokens
    gone = runs.filter(~F.col("weak") | (long & carrier))
    gone = gone.withColumn("inside", long & (carrier | ~F.col("some_weak")) & (F.col("begins") == 0))
    gone = gone.groupBy("id", "th").agg(F.sort_array(F.collect_list(F.struct("i", "inside"))).alias("gone"))
    before = lambda k: F.coalesce(F.get("gone", k - 1)["i"], F.lit(-1))
    flags = F.transform("gone", lambda g, k: F.concat(F.array_repeat(F.when(g["inside"], 2).otherwise(0), g["i"] - before(k) - 1), F.array(F.lit(1))))
    return gone.select("id", "th", F.flatten(flags).alias("flags"))


def token_count(record: Column) -> Column:
    trimmed = F.rtrim(record, F.lit(" \n"))
    return F.octet_length(trimmed) - F.octet_length(F.replace(trimmed, F.lit(" "), F.lit(""))) + 1


def _fielded(thin: DataFrame, leaves: DataFrame, open_tpls: DataFrame, rules: Rules) -> DataFrame:
    """(tpl, template) for records of open leaves whose rare tokens are variable fields, where the result recurs.

    A table of occupied slots, bounded by ``SLOTS``, keeps most records of other leaves from
    the shuffle.
    """
    slot = F.pmod(F.col("leaf"), F.lit(SLOTS)).alias("slot")
    slots = leaves.select(slot).distinct()
    near = thin.filter(F.col("n") >= rules.min_tokens).select("leaf", "tpl", "th", "n", "shape", slot).join(F.broadcast(slots), "slot", "left_semi")
    own = settle_table(join_unique(near, open_tpls, ["tpl"], ["th"]).select("leaf", "tpl", "th", "n", "shape").dropDuplicates(["tpl", "th"]))
    tokens = own.select("leaf", "tpl", "th", "n", F.posexplode(F.split("shape", " ")).alias("at", "token"))
    common = tokens.groupBy("leaf", "at", "token").agg(F.count(F.lit(1)).alias("c")).filter((F.col("c") >= rules.min_docs) & (F.col("token") != FIELD)).drop("c")
    kept = join_unique(tokens, common, ["leaf", "at", "token"], ["tpl", "th"])
    shapes = kept.groupBy("leaf", "tpl", "th").agg(F.max("n").alias("n"), F.sort_array(F.collect_list(F.struct("at", "token"))).alias("constants"))
    shapes = settle_table(shapes.filter(F.size("constants") >= rules.constant * F.col("n")).select("tpl", "th", F.xxhash64("leaf", "constants").alias("template")))
    shared = _texts(shapes, ["template"]).filter(F.col("texts") >= rules.min_docs).select("template")
    return join_unique(shapes.select("tpl", "template").distinct(), shared, ["template"], ["tpl"]).select("tpl", "template")


def drop_recurring(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules: Rules = Rules(), report: bool = False) -> DataFrame:
    """The documents with the records of recurring templates removed, all columns kept.

    The first record of a template (smallest id, then place) stays, so nothing that the
    corpus says is lost; null ids come first.  With ``report`` instead: id, n_records,
    n_dropped, text.  Every row stays, if need be with an empty text; null texts stay null.
    Rows repeated with one id and text lose the same records; copies of a text count as one
    document.  An empty table gives no rows.  Records are cut by pattern, so a long line or
    text is only a longer row.  Templates and texts are compared by 64-bit hashes: a
    collision would count different records as one template.
    """
    gone = recurring(docs, id_col, text_col, rules).select(F.col("id").alias("__id"), F.col("th").alias("__th"), F.col("flags").alias("__flags"))
    base = docs.select("*", F.xxhash64(text_col).alias("__h"))
    joined = base.join(gone, base[id_col].eqNullSafe(gone["__id"]) & (base["__h"] == gone["__th"]), "left")
    text = F.col(text_col)

    def stays(x: Column, i: Column) -> Column:
        flag = F.coalesce(F.get("__flags", i), F.lit(0))
        return (flag == 0) | ((flag == 2) & (token_count(x) >= rules.min_tokens))

    joined = joined.withColumn("__left", F.when(F.col("__flags").isNotNull(), F.filter(record_list(text), stays)))
    kept = F.when(F.col("__flags").isNull(), text).otherwise(F.array_join("__left", ""))  # no record gone: the text as it was
    if report:
        n = F.coalesce(record_count(text), F.lit(0))
        return joined.select(
            F.col(id_col),
            n.alias("n_records"),
            F.when(F.col("__flags").isNull(), 0).otherwise(n - F.size("__left")).alias("n_dropped"),
            kept.alias("text"),
        )
    return joined.select(*(kept.alias(c) if c == text_col else F.col(c) for c in docs.columns))
