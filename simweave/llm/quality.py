"""Quality rules of documents and of their hosts, in DataFrame functions only.

Rule failures are aggregated by host, each host's failure rate is shrunk towards an empirical beta prior, and the
host verdicts are joined back to the documents.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from simweave.plans.staging import broadcast_if_small, stage

#: White space between words, as the class of a pattern and as its characters.
SPACE_CLASS = "[\\x20\\x09-\\x0D]"
SPACES = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"
#: Fixed limits of the document rules: fewest words; largest share of repeated words in percent.
LEAST_WORDS, REPEAT_PERCENT = 50, 50
#: A host is rejected when its shrunk failure rate is above this.
HOST_RATE = 0.5


def _let(value: Column, body) -> Column:
    """body(value) with value computed once a row."""
    return F.transform(F.array(value), body)[0]


def _words_in_repeated_windows(words: Column) -> Column:
    """Words covered by a window of 3 that occurs at least twice; windows are told apart by 64-bit hashes."""

    def covered(starts: Column) -> Column:
        gain = F.transform(starts, lambda p, k: F.least(F.lit(3), p - F.coalesce(F.get(starts, k - 1), F.lit(-3))))
        return F.aggregate(gain, F.lit(0).cast("long"), lambda a, x: a + x)

    def repeated(ranked: Column) -> Column:
        same = lambda e, k: F.coalesce(F.get(ranked, k)["h"] == e["h"], F.lit(False))
        kept = F.filter(ranked, lambda e, k: same(e, k - 1) | same(e, k + 1))
        return _let(F.sort_array(F.transform(kept, lambda e: e["i"])), covered)

    def ranked(hashes: Column) -> Column:
        pairs = F.sort_array(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        return F.when(F.size(F.array_distinct(hashes)) == F.size(hashes), F.lit(0).cast("long")).otherwise(_let(pairs, repeated))

    heads = F.slice(words, 1, F.greatest(F.size(words) - 2, F.lit(0)))
    return _let(F.transform(heads, lambda w, i: F.xxhash64(w, F.get(words, i + 1), F.get(words, i + 2))), ranked)


def measure_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", carry: str | None = None) -> DataFrame:
    """doc_id, host, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and base_failed of each row.

    Null text has no words; an empty or very long text is measured whole. No shuffle; of the
    other columns only carry is passed through.
    """
    slim = docs.select(F.col(id_col).alias("doc_id"), F.col(host_col).alias("host"), F.coalesce(F.col(text_col), F.lit("")).alias("t"), *([carry] if carry else []))
    trimmed = F.btrim("t", F.lit(SPACES))
    words = F.split(trimmed, f"{SPACE_CLASS}+", -1)

    def lines(text: Column) -> Column:
        full = F.filter(F.split(text, "\n", -1), lambda x: F.btrim(x, F.lit(SPACES)) != "")
        return _let(full, lambda f: (F.size(f) - F.size(F.array_distinct(f))).cast("long"))

    counted = slim.select(
        "doc_id",
        "host",
        *([carry] if carry else []),
        F.char_length(F.translate("t", SPACES, "")).cast("long").alias("word_chars"),
        (F.char_length("t") - F.char_length(F.translate("t", SYMBOLS, ""))).cast("long").alias("n_symbols"),
        lines(F.col("t")).alias("n_dup_lines"),
        F.when(trimmed == "", F.struct(F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("r")))
        .otherwise(_let(words, lambda w: F.struct(F.size(w).cast("long").alias("n"), _words_in_repeated_windows(w).alias("r"))))
        .alias("w"),
    )
    return counted.select(
        "doc_id", "host", *([carry] if carry else []), F.col("w.n").alias("n_words"), "word_chars", "n_symbols", "n_dup_lines", F.col("w.r").alias("n_repeat_words")
    ).withColumn("base_failed", (F.col("n_words") < LEAST_WORDS) | (100 * F.col("n_repeat_words") > REPEAT_PERCENT * F.col("n_words")))


def host_rates(measured: DataFrame) -> DataFrame:
    """host, n_docs, n_failed, rate and shrunk_rate; a null host is a host of its own.

    The prior's mean and variance are those of the host rates; its strength is mean(1-mean)/variance - 1, held within
    [1, 1e6], so hosts without any spread shrink to the common mean.
    """
    hosts = measured.groupBy("host").agg(F.count(F.lit(1)).alias("n_docs"), F.sum(F.col("base_failed").cast("long")).alias("n_failed"))
    hosts = hosts.withColumn("rate", F.col("n_failed") / F.col("n_docs"))
    # decimal sums, so that the prior does not depend on the order of hosts
    exact = F.col("rate").cast("decimal(14,12)")
    sums = hosts.agg(F.sum(exact).cast("double").alias("s"), F.sum((exact * exact).cast("decimal(25,24)")).cast("double").alias("q"), F.count(F.lit(1)).alias("k"))
    prior = sums.select((F.col("s") / F.col("k")).alias("mean"), (F.col("q") / F.col("k") - F.pow(F.col("s") / F.col("k"), F.lit(2.0))).alias("spread"))
    strength = F.when(F.col("spread") > 0, F.greatest(F.least(F.col("mean") * (1 - F.col("mean")) / F.col("spread") - 1, F.lit(1e6)), F.lit(1.0))).otherwise(F.lit(1e6))
    prior = prior.select("mean", strength.alias("strength"))
    return hosts.join(F.broadcast(prior)).select(
        "host", "n_docs", "n_failed", "rate",
        ((F.col("n_failed") + F.col("mean") * F.col("strength")) / (F.col("n_docs") + F.col("strength"))).alias("shrunk_rate"),
    )


def judge_documents(docs: DataFrame, host_rate: float = HOST_RATE, **columns: str) -> DataFrame:
    """measure_documents() with shrunk_rate of the host and kept.

    A document stays if it passes the document rules and its host's shrunk rate is at most host_rate. Repeated rows are
    judged each; an empty table gives an empty result. The per-document measures are computed once and staged.
    """
    measured = stage(measure_documents(docs, **columns), "measured")
    hosts = host_rates(measured).select("host", "shrunk_rate")
    return (
        measured.join(hosts, measured["host"].eqNullSafe(hosts["host"])).drop(hosts["host"])
        .withColumn("kept", ~F.col("base_failed") & (F.col("shrunk_rate") <= host_rate))
    )


def keep_good_documents(docs: DataFrame, host_rate: float = HOST_RATE, id_col="doc_id", text_col="text", host_col="source") -> DataFrame:
    """The rows of docs that judge_documents() keeps, with their own columns.

    Rows are staged together with their verdict, so no join by id moves the texts; host verdicts are joined to them.
    """
    own = "__base_failed"
    measured = measure_documents(docs.select(F.struct("*").alias("__row")), f"__row.{id_col}", f"__row.{text_col}", f"__row.{host_col}", carry="__row")
    rows = stage(measured.select("__row", F.col("host").alias("__host"), F.col("base_failed").alias(own)), "judged-rows")
    rates = host_rates(rows.select(F.col("__host").alias("host"), F.col(own).alias("base_failed")))
    bad = stage(rates.where(F.col("shrunk_rate") > host_rate).select(F.col("host").alias("__bad")), "bad-hosts")
    good = rows.where(~F.col(own)).join(broadcast_if_small(bad, 256), F.col("__host").eqNullSafe(F.col("__bad")), "left_anti")
    return good.select("__row.*")
