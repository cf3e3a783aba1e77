"""Text workloads: resemblance, containment and shared vocabularies, exactly and by maximum likelihood.

The estimator runs on bucketed sketches, two hashes an element whatever m is; beside each exact answer stands whether
the estimate lies within four standard errors of it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setoverlap.functions import textsets
from setoverlap.functions.hashing import element_hash
from setoverlap.operators import allpairs, cardinality, exact, mle, pairstats, prefixes, registers
from setoverlap.operators.theory import crb_intersection
from setoverlap.plans import sql, workloads as w
from setoverlap.plans.book import query, within
from setoverlap.session import materialised
from setoverlap.sources.tables import load_table

SKETCH = {"family": "xxhash64", "layout": "bucketed"}
M = 1024


def error_at(a, b, n, m: int):
    """Standard error that the information bound allows at exact sizes."""
    d = lambda c: F.col(c).cast("double")
    return F.sqrt(crb_intersection(d(a), d(b), d(n), F.lit(float(m))))


def beside_exact(rows: DataFrame, by: list[str] | tuple = (), m: int = M) -> DataFrame:
    """by..., the exact sizes of (e, in_a, in_b), and `close`: the estimate of card_both within four standard errors."""
    est = mle.mle_intersection(w.stats_of(rows, list(by), m, **SKETCH)).select(*by, F.col("card_both").alias("estimate"))
    true = exact.exact_sizes(rows, "e", F.col("in_a"), F.col("in_b"), list(by))
    both = true.join(est, list(by)) if by else true.crossJoin(est)  # one row each
    return both.withColumn("close", within(F.col("estimate"), F.col("card_both"), error_at("card_a", "card_b", "card_both", m), slack=2.0)).drop("estimate")


def pairs_beside_exact(sets: DataFrame, group: str, m: int = M) -> DataFrame:
    """x, y, exact card_both of all group pairs that share an element, and `close`; groups must be few."""
    regs = registers.build_registers(sets, "e", [group], m, **SKETCH)
    est = mle.mle_intersection(pairstats.pair_stats_all(regs, group, m, layout="bucketed")).select("x", "y", F.col("card_both").alias("estimate"))
    true = allpairs.exact_pair_overlaps(sets, group, "e")
    n = sets.select(group, "e").distinct().groupBy(group).agg(F.count("*").alias("n"))
    got = true.join(est, ["x", "y"]).join(F.broadcast(n.toDF("x", "card_a")), "x").join(F.broadcast(n.toDF("y", "card_b")), "y")  # at most MOST_GROUPS rows
    return got.select("x", "y", "card_both", within(F.col("estimate"), F.col("card_both"), error_at("card_a", "card_b", "card_both", m), slack=2.0).alias("close"))


def _sizes(src: str, by: str = "") -> str:
    return f"SELECT *, true AS close FROM ({sql.exact_flags(src, by)}) f"


for _name, _src, _sql in (("year", w.customers_by_year, w.S_YEAR), ("status", w.customers_by_status, w.S_STATUS), ("return", w.orders_by_return, w.S_RETURN), ("keys", w.join_keys, w.S_KEYS)):
    def _run(spark, d, src=_src):
        return beside_exact(src(spark, d))

    query(_sizes(_sql), f"ml_bucketed_{_name}")(_run)


@query(_sizes(w.S_FLOWS, "day"))
def ml_bucketed_flows_daily(spark, d):
    return beside_exact(w.shared_flows(spark, d), ["day"])


# --- documents ------------------------------------------------------------------------------------------------------------------

_SH = r"SELECT DISTINCT doc_id, array_to_string(ws[i : i + 4], ' ') AS e FROM (SELECT doc_id, string_split_regex(lower(trim(text)), '\s+') AS ws FROM documents) q, unnest(range(1, greatest(len(ws) - 3, 2))) u(i)"
_NEAR = f"""WITH s AS ({_SH}), l AS (SELECT doc_id, md5(string_agg(e, chr(1) ORDER BY e)) AS k, count(*) AS n FROM s GROUP BY 1),
n AS (SELECT doc_id, n, min(doc_id) OVER (PARTITION BY k) AS r FROM l), t AS (SELECT s.* FROM s JOIN n USING (doc_id) WHERE n.r = n.doc_id),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM t a JOIN t b ON a.e = b.e AND a.doc_id < b.doc_id GROUP BY 1, 2)
SELECT x, y, c AS card_both, h.n + k.n - c AS card_any FROM p JOIN n h ON h.doc_id = x JOIN n k ON k.doc_id = y WHERE 2 * c >= h.n + k.n - c
UNION ALL SELECT r, doc_id, n, n FROM n WHERE r <> doc_id"""


@query(_NEAR)
def doc_near_duplicates_exact(spark, d):
    """Pairs at Jaccard .5 or more between classes of equal shingle sets, and each copy beside its class."""
    return prefixes.similar_pairs(w.document_rows(spark, d), "doc_id", w.shingle_hashes(), 1, 2)


#: 32 bands of 2 of the 64 registers: a pair at Jaccard .5 becomes a candidate with probability .9999.
BAND, DOC_M = 2, 64


def _document_sketches(spark, d):
    """(doc_id, regs), written once: 8 bytes a register and document."""
    sets = w.document_rows(spark, d).select("doc_id", w.shingle_hashes(element_hash).alias("h"))
    return materialised(registers.sketch_arrays(sets, "doc_id", DOC_M))


@query()
def doc_near_duplicates_ml(spark, d):
    """Candidates by bands, sizes and Jaccard by maximum likelihood; classes of equal sketches are compared once
    (doc_sketch_classes lists their members). doc_near_duplicates_recall holds it to the exact pairs."""
    got = mle.mle_intersection(allpairs.similar_pairs(_document_sketches(spark, d), "doc_id", DOC_M, BAND), engine="arrow")
    return got.where("jaccard >= 0.5").select("x", "y", "card_both", "jaccard")


@query()
def doc_sketch_classes(spark, d):
    """member, class: documents whose sketches are equal."""
    return allpairs.members(_document_sketches(spark, d), "doc_id", "regs")


@query()
def doc_banding_candidates(spark, d):
    return allpairs.packed_candidates(_document_sketches(spark, d), "doc_id", BAND)


@query("SELECT true AS recall_at_least_9_tenths, true AS estimates_close")
def doc_near_duplicates_recall(spark, d):
    """Of the exact pairs at Jaccard .5, at least nine tenths share a class of equal sketches or are candidates, and of
    these at least 98 % have a maximum-likelihood size within four standard errors of the exact one."""
    exact_pairs, sketches = doc_near_duplicates_exact(spark, d), _document_sketches(spark, d)
    of = allpairs.members(sketches, "doc_id", "regs")
    est = mle.estimate_interval(mle.mle_intersection(allpairs.similar_pairs(sketches, "doc_id", DOC_M, BAND), engine="arrow")).select(F.col("x").alias("cx"), F.col("y").alias("cy"), F.col("card_both").alias("estimate"), "std_err")
    placed = exact_pairs.join(of.toDF("x", "px"), "x").join(of.toDF("y", "py"), "y").withColumns({"cx": F.least("px", "py"), "cy": F.greatest("px", "py")})
    got = placed.join(est, ["cx", "cy"], "left").withColumn("found", (F.col("cx") == F.col("cy")) | F.col("estimate").isNotNull())
    near = within(F.col("estimate"), F.col("card_both"), F.col("std_err"), slack=2.0)
    return got.agg((F.avg(F.col("found").cast("double")) >= 0.9).alias("recall_at_least_9_tenths"), (F.coalesce(F.avg(F.when(F.col("estimate").isNotNull(), near.cast("double"))), F.lit(1.0)) >= 0.98).alias("estimates_close"))


_BSH = _SH.replace("documents", "benchmark").replace("doc_id", "item_id")
_HELD = f"WITH s AS ({_SH}), b AS ({_BSH}), n AS (SELECT item_id, count(*) AS n FROM b GROUP BY 1) SELECT item_id, doc_id, count(*) AS card_both, any_value(n.n) AS card_a FROM b JOIN s USING (e) JOIN n USING (item_id) GROUP BY 1, 2 HAVING 2 * count(*) >= any_value(n.n)"


def _item_shingles(spark, d):
    return load_table(spark, d, "benchmark").select("item_id", F.explode(textsets.shingles(F.col("text"))).alias("e"))


@query(_HELD)
def benchmark_containment(spark, d):
    items = _item_shingles(spark, d)
    n = items.groupBy("item_id").agg(F.count("*").alias("card_a"))
    got = items.join(w.document_shingles(spark, d), "e").groupBy("item_id", "doc_id").agg(F.count("*").alias("card_both"))
    return got.join(n, "item_id").where("2 * card_both >= card_a").select("item_id", "doc_id", "card_both", "card_a")


@query(f"SELECT item_id, doc_id, card_both, true AS close FROM ({_HELD}) h")
def benchmark_containment_ml(spark, d):
    """Plagiarism at a size ratio far from 1: how much of a short passage a long document holds, estimated from 1,024 buckets."""
    held = benchmark_containment(spark, d)
    sketch = lambda sets, g: registers.build_registers(sets, "e", [g], M, **SKETCH)
    docs = w.document_shingles(spark, d).join(held.select("doc_id").distinct(), "doc_id", "left_semi")
    stats = pairstats.pair_stats_two(sketch(_item_shingles(spark, d), "item_id"), "item_id", sketch(docs, "doc_id"), "doc_id", held.select(F.col("item_id").alias("x"), F.col("doc_id").alias("y")), M, layout="bucketed")
    est = mle.mle_intersection(stats).select(F.col("x").alias("item_id"), F.col("y").alias("doc_id"), F.col("card_b").alias("est_b"), F.col("card_both").alias("estimate"))
    got = held.join(est, ["item_id", "doc_id"]).withColumn("est_b", F.greatest("est_b", "card_both"))
    return got.select("item_id", "doc_id", "card_both", within(F.col("estimate"), F.col("card_both"), error_at("card_a", "est_b", "card_both", M), slack=2.0).alias("close"))


# --- vocabularies, lines, links, turns, cells --------------------------------------------------------------------------------------

def _labelled(spark, d, label):
    docs = load_table(spark, d, "documents").join(load_table(spark, d, "labels"), "doc_id")
    return docs.select(F.explode(F.array_distinct(textsets.words(F.col("text")))).alias("e"), (F.col(label) == 0).alias("in_a"), (F.col(label) == 1).alias("in_b"))


for _lab in ("quality", "toxic"):
    _words = rf"SELECT unnest(string_split_regex(lower(text), '\s+')) AS e, {_lab} = 0 AS in_a, {_lab} = 1 AS in_b FROM documents JOIN labels USING (doc_id)"

    def _run(spark, d, lab=_lab):
        return exact.exact_sizes(_labelled(spark, d, lab), "e", F.col("in_a"), F.col("in_b"))

    def _est(spark, d, lab=_lab):
        return beside_exact(_labelled(spark, d, lab))

    query(sql.exact_flags(_words), f"label_vocab_overlap_{_lab}")(_run)
    query(_sizes(_words), f"label_vocab_ml_{_lab}")(_est)


def _pairs_sql(sets: str, extra: str = "", where: str = "") -> str:
    """Shared elements of group pairs, of a query giving distinct (g, e)."""
    return f"WITH s AS ({sets}) SELECT a.g AS x, b.g AS y, count(*) AS card_both{extra} FROM s a JOIN s b ON a.e = b.e AND a.g < b.g {where} GROUP BY 1, 2"


_LINES = "SELECT DISTINCT source AS g, trim(unnest(string_split(text, chr(10)))) AS e FROM documents"


def _source_lines(spark, d):
    return load_table(spark, d, "documents").select("source", F.explode(textsets.lines(F.col("text"))).alias("e"))


@query(_pairs_sql(_LINES, where="WHERE a.e <> ''"))
def line_boilerplate_sources(spark, d):
    return allpairs.exact_pair_overlaps(_source_lines(spark, d), "source", "e").select("x", "y", "card_both")


@query(_pairs_sql(_LINES, ", true AS close", "WHERE a.e <> ''"))
def line_boilerplate_sources_ml(spark, d):
    return pairs_beside_exact(_source_lines(spark, d), "source", 4096)


_LANG_WORDS = r"SELECT DISTINCT lang AS g, unnest(string_split_regex(lower(text), '\s+')) AS e FROM documents"


@query(_pairs_sql(_LANG_WORDS, ", true AS close"))
def vocabulary_pairs_ml(spark, d):
    return pairs_beside_exact(w.language_words(spark, d), "lang", 4096)


@query(rf"SELECT lang, count(DISTINCT e) AS card FROM (SELECT lang, unnest(string_split_regex(lower(text), '\s+')) AS e FROM documents) q GROUP BY 1")
def vocabulary_sizes(spark, d):
    return cardinality.exact_cardinality(w.language_words(spark, d), "e", ["lang"])


_ROLE = r"SELECT unnest(string_split_regex(lower(text), '\s+')) AS e, role = 'user' AS in_a, role = 'assistant' AS in_b FROM conversations"


def _role_words(spark, d):
    return load_table(spark, d, "conversations").select("conv_id", F.explode(F.array_distinct(textsets.words(F.col("text")))).alias("e"), (F.col("role") == "user").alias("in_a"), (F.col("role") == "assistant").alias("in_b"))


@query(sql.exact_flags(_ROLE))
def role_vocab(spark, d):
    return exact.exact_sizes(_role_words(spark, d), "e", F.col("in_a"), F.col("in_b"))


@query(_sizes(_ROLE))
def role_vocab_ml(spark, d):
    return beside_exact(_role_words(spark, d))


@query(_sizes(_ROLE.replace("SELECT unnest", "SELECT conv_id, unnest"), "conv_id"))
def conversation_vocab_ml(spark, d):
    """What user and assistant share in each conversation."""
    return beside_exact(_role_words(spark, d), ["conv_id"], 256)


@query(r"SELECT h AS host, count(DISTINCT e) AS card FROM (SELECT regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS h, unnest(string_split_regex(lower(regexp_replace(html, '<[^>]*>', ' ', 'g')), '\s+')) AS e FROM pages) q GROUP BY 1")
def page_host_words(spark, d):
    p = load_table(spark, d, "pages").select(textsets.host(F.col("url")).alias("host"), F.explode(F.array_distinct(textsets.words(textsets.stripped(F.col("html"))))).alias("e"))
    return cardinality.exact_cardinality(p, "e", ["host"])


@query("SELECT page_id, len(list_distinct(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1))) AS n_links FROM pages")
def page_links(spark, d):
    return load_table(spark, d, "pages").select("page_id", F.size(textsets.links(F.col("html"))).cast("long").alias("n_links"))


@query(_pairs_sql("SELECT DISTINCT page_id AS g, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS e FROM pages"))
def page_pairs_shared_links(spark, d):
    """Links that two pages share, for every pair that shares one."""
    links = load_table(spark, d, "pages").select("page_id", F.explode(textsets.links(F.col("html"))).alias("e"))
    return allpairs.exact_pair_overlaps(links, "page_id", "e").select("x", "y", "card_both")


def _code(bits: int) -> str:
    return " + ".join(f"CASE WHEN embedding[{i + 1}] > 0 THEN {1 << i} ELSE 0 END" for i in range(bits))


def _cells(spark, d, bits: int):
    code = F.lit(0)
    for i in range(bits):
        code = code + F.when(F.get("embedding", F.lit(i)) > 0, 1 << i).otherwise(0)
    return load_table(spark, d, "embeddings").select("label", code.alias("e"))


@query(_pairs_sql(f"SELECT DISTINCT label AS g, {_code(8)} AS e FROM embeddings"))
def embedding_cells(spark, d):
    return allpairs.exact_pair_overlaps(_cells(spark, d, 8), "label", "e").select("x", "y", "card_both")


@query(_pairs_sql(f"SELECT DISTINCT label AS g, {_code(10)} AS e FROM embeddings", ", true AS close"))
def embedding_cells_ml(spark, d):
    return pairs_beside_exact(_cells(spark, d, 10), "label", 4096)


@query("SELECT (from_json(props, '{\"k\":\"BIGINT\"}')).k AS k, count(DISTINCT user_id) AS card FROM events GROUP BY 1")
def users_by_property(spark, d):
    return cardinality.exact_cardinality(load_table(spark, d, "events").withColumn("k", F.get_json_object("props", "$.k").cast("long")), "user_id", ["k"])
