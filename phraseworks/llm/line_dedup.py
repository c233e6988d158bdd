"""Cross-site boilerplate lines, found by the number of distinct sites a line is on.

Every line's hash gets a HyperLogLog sketch of its sites; sketches merge in the aggregation. Estimates far from the
threshold decide at once, lines whose estimate is near it get an exact distinct count. A line on at least
``min_sites`` sites is boilerplate: it stays in the document with the smallest id that has it and goes from all others.

Edge cases: lines compare after trimming blanks, tabs and carriage returns; blank lines are never counted or removed;
null text stays null and has no lines; a null site counts as no site; a null id neither keeps nor loses lines of its
own (its text is unchanged); repeated rows of one id count as one document; other columns pass through unread, whatever their
names; an empty table gives an empty table. A line is its 64-bit hash: two that collide count as one.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import settle

#: Boilerplate lines that may travel to the tasks (16 bytes each); more of them are joined.
FEW = 100_000
#: Sketches of 2^12 registers have a relative error of about 1.6 %.
LOG_REGISTERS = 12
#: Relative distance from the threshold, some six standard errors, within which an estimate does not decide.
NEAR = 0.1


def _key(line: Column) -> Column:
    return F.xxhash64(F.trim(line, F.lit(" \t\r")))


def _lines(docs: DataFrame, id_col: str, text_col: str, site_col: str) -> DataFrame:
    """A row for each line that isn't blank: key, doc, site. A document's repeated lines stay apart; sums take care of them."""
    keys = F.transform(F.filter(F.split(F.col(text_col), "\n", -1), lambda x: F.length(F.trim(x, F.lit(" \t\r"))) > 0), _key)
    return docs.select(F.explode(F.array_distinct(keys)).alias("key"), F.col(id_col).alias("doc"), F.col(site_col).alias("site"))


def boilerplate(docs: DataFrame, min_sites: int = 10, id_col: str = "doc_id", text_col: str = "text", site_col: str = "source") -> DataFrame:
    """Boilerplate lines: key, keeper (smallest document id that has the line), sites (estimate, exact near the threshold)."""
    lines = _lines(docs, id_col, text_col, site_col)
    sketched = lines.groupBy("key").agg(F.count("*").alias("n"), F.min("doc").alias("keeper"), F.hll_sketch_agg(F.col("site").cast("string"), LOG_REGISTERS).alias("sketch"))
    # fewer rows than sites can't reach the threshold whatever the sketch says
    judged = settle(sketched.where(F.col("n") >= min_sites).select("key", "keeper", F.hll_sketch_estimate("sketch").alias("sites")).where(F.col("sites") >= min_sites * (1 - NEAR)), "line-sites")
    near = judged.where(F.col("sites") <= min_sites * (1 + NEAR))
    exact = lines.join(near.select("key"), "key", "left_semi").groupBy("key", "site").agg(F.lit(1).alias("one")).groupBy("key").agg(F.count("site").alias("sites"))
    decided = near.drop("sites").join(exact, "key").where(F.col("sites") >= min_sites)
    return settle(judged.where(F.col("sites") > min_sites * (1 + NEAR)).unionByName(decided), "boilerplate")


def _dropped_in_place(docs: DataFrame, found: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """The removal in one pass without a shuffle, by at most FEW lines that go with the tasks."""
    table = found.select("key", "keeper").orderBy("key").toArrow()  # at most FEW rows
    # nothing is greater than the keeper of lines that only rows without an id have
    keys, keepers = table.column("key").to_numpy(), pc.fill_null(table.column("keeper"), np.iinfo(np.int64).max).to_numpy()
    names, at = docs.columns, docs.columns.index(text_col)
    hashed = docs.select("*", F.transform(F.split(F.col(text_col), "\n", -1), lambda x: F.when(F.length(F.trim(x, F.lit(" \t\r"))) > 0, _key(x))), F.col(id_col).cast("long"))
    hashed = hashed.toDF(*[f"c{i}" for i in range(len(names) + 2)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lines, owner = batch.column(len(names)), batch.column(len(names) + 1)
            flat = lines.flatten()
            own = pc.list_parent_indices(lines).to_numpy()
            line = flat.to_numpy(zero_copy_only=False) if flat.null_count == 0 else pc.fill_null(flat, 0).to_numpy(zero_copy_only=False)
            place = np.minimum(np.searchsorted(keys, line), max(0, len(keys) - 1))
            docs_of = pc.fill_null(owner, np.iinfo(np.int64).min).to_numpy(zero_copy_only=False)[own]
            gone = (keys[place] == line) & flat.is_valid().to_numpy(zero_copy_only=False) & (docs_of > keepers[place]) if len(keys) else np.zeros(len(line), bool)
            counts = np.bincount(own[gone], minlength=batch.num_rows)
            text, texts = batch.column(at), batch.column(at)
            if gone.any():
                texts = text.to_pylist()
                ends = np.searchsorted(own, np.arange(batch.num_rows + 1))
                for i in np.flatnonzero(counts).tolist():
                    texts[i] = "\n".join(x for x, g in zip(texts[i].split("\n"), gone[ends[i] : ends[i + 1]].tolist(), strict=True) if not g)
                texts = pa.array(texts, text.type)
            out = [texts if i == at else batch.column(i) for i in range(len(names))]
            yield pa.RecordBatch.from_arrays([*out, pa.array(counts, pa.int64())], [f"c{i}" for i in range(len(names))] + ["dropped"])

    from pyspark.sql.types import LongType, StructField, StructType

    schema = StructType([StructField(f"c{i}", f.dataType) for i, f in enumerate(docs.schema)] + [StructField("dropped", LongType())])
    return hashed.mapInArrow(run, schema).toDF(*names, "dropped_lines")


def drop_boilerplate(docs: DataFrame, min_sites: int = 10, id_col: str = "doc_id", text_col: str = "text", site_col: str = "source") -> DataFrame:
    """docs with boilerplate lines taken out of the text; every row stays. Adds dropped_lines (long) behind docs' columns."""
    found = boilerplate(docs, min_sites, id_col, text_col, site_col)
    names = [c for c in docs.columns if c != "dropped_lines"]
    if found.count() <= FEW:
        return _dropped_in_place(docs.select(*names), found, id_col, text_col)
    lines = _lines(docs, id_col, text_col, site_col)
    drops = lines.join(found, "key").where(F.col("doc") > F.col("keeper")).groupBy(F.col("doc").alias("drop_of")).agg(F.collect_set("key").alias("drop_keys"))
    # the rows travel as one struct, so that no column of theirs meets a name used here
    rows = docs.select(F.struct(*names).alias("row"), F.col(id_col).alias("row_id")).join(drops, F.col("row_id") == F.col("drop_of"), "left")
    text, bad = F.col("row").getField(text_col), F.col("drop_keys")
    split = F.split(text, "\n", -1)
    stays = F.filter(split, lambda x: ~((F.length(F.trim(x, F.lit(" \t\r"))) > 0) & F.array_contains(bad, _key(x))))
    hit = bad.isNotNull() & text.isNotNull()
    done = rows.select("row", F.when(hit, F.array_join(stays, "\n")).otherwise(text).alias("kept"), F.when(hit, F.size(split) - F.size(stays)).otherwise(0).cast("long").alias("gone"))
    return done.select(*[(F.col("kept") if c == text_col else F.col("row").getField(c)).alias(c) for c in names], F.col("gone").alias("dropped_lines"))
