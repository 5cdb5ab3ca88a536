"""Shingles, signatures, buckets, clusters, accuracy, and the baselines of deduplication."""

from __future__ import annotations

from pyspark.sql import functions as F

from mlcurate.dedup import minhash as H
from mlcurate.io import table
from mlcurate.session import settle
from mlcurate.workloads import sql as S
from mlcurate.workloads.registry import query

CFG = H.Config()
_A, _B = ([str(c[i]) for c in CFG.coefficients] for i in (0, 1))
N = CFG.bands * CFG.rows
SHINGLES = f"""wd AS (SELECT doc_id, lang, source, {S.WORDS} AS w FROM documents),
sh AS (SELECT DISTINCT doc_id, lang, source, ('0x' || substr(md5(s), 1, 7))::BIGINT AS g FROM (SELECT doc_id, lang, source, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')] ELSE {S.grams("w", 5)} END) AS s FROM wd))"""
SIGS = f"""{SHINGLES},
co AS (SELECT unnest([{", ".join(_A)}])::BIGINT AS a, unnest([{", ".join(_B)}])::BIGINT AS b, unnest(range({N})) AS i),
sg AS (SELECT doc_id, lang, source, i, min((g * a + b) % {H.PRIME}) AS m FROM sh CROSS JOIN co GROUP BY ALL),
sig AS (SELECT doc_id, lang, source, list(m ORDER BY i) AS sig FROM sg GROUP BY ALL)"""
BANDS = f"""{SIGS},
bands AS (SELECT doc_id, lang, source, band::INT AS band, md5(array_to_string(sig[band * {CFG.rows} + 1 : band * {CFG.rows} + {CFG.rows}], ',')) AS bkey FROM sig, range({CFG.bands}) r(band))"""


def clusters_sql(scope: str = "lang", start: str = BANDS) -> str:
    return f"""{start},
ed AS (SELECT DISTINCT doc_id AS src, min(doc_id) OVER (PARTITION BY {scope}, band, bkey) AS dst FROM bands),
und AS (SELECT src, dst FROM ed WHERE src <> dst UNION SELECT dst, src FROM ed WHERE src <> dst),
reach AS (SELECT doc_id AS id, doc_id AS c FROM documents UNION SELECT reach.id, und.dst FROM reach JOIN und ON reach.c = und.src),
cl AS (SELECT id AS doc_id, min(c) AS comp FROM reach GROUP BY id),
clusters AS (SELECT doc_id, d.lang, d.source, comp, count(*) OVER (PARTITION BY comp) AS cluster_size, doc_id = comp AS keep FROM cl JOIN documents d USING (doc_id))"""


CLUSTERS = clusters_sql()


@query(S.with_(SHINGLES, "SELECT doc_id, lang, count(*) AS n, min(g) AS least, bit_xor(g) AS mix FROM sh GROUP BY ALL"))
def w_shingles(spark, sf_dir):
    g = H.shingles(table(spark, sf_dir, "documents"), CFG).distinct()
    return g.groupBy("doc_id", "lang").agg(F.count(F.lit(1)).alias("n"), F.min("g").alias("least"), F.bit_xor("g").alias("mix"))


@query(S.with_(SIGS, "SELECT doc_id, lang, md5(array_to_string(sig, ',')) AS sig_md5 FROM sig"))
def w_minhash_sig(spark, sf_dir):
    s = H.signatures(table(spark, sf_dir, "documents"), CFG)
    return s.select("doc_id", "lang", F.md5(F.array_join(F.col("sig").cast("array<string>"), ",")).alias("sig_md5"))


def bands(spark, sf_dir, keep=("doc_id", "lang")):
    return H.band_keys(H.signatures(table(spark, sf_dir, "documents"), CFG, keep), CFG, keep)


@query(S.with_(BANDS, "SELECT doc_id, lang, band, bkey FROM bands"))
def w_band_keys(spark, sf_dir):
    return bands(spark, sf_dir)


@query(S.with_(CLUSTERS, "SELECT src, dst FROM ed WHERE src <> dst"))
def w_star_edges(spark, sf_dir):
    return H.star_edges(bands(spark, sf_dir))


def clusters(spark, sf_dir, scope=("lang",), algo="star"):
    return settle(H.clusters(table(spark, sf_dir, "documents"), CFG, scope, algo), "clusters")


@query(S.with_(CLUSTERS, "SELECT doc_id, lang, comp, cluster_size, keep FROM clusters"))
def w_clusters(spark, sf_dir):
    return clusters(spark, sf_dir)


@query(S.with_(CLUSTERS, "SELECT doc_id, comp FROM clusters"))
def w_clusters_minlabel(spark, sf_dir):
    return clusters(spark, sf_dir, algo="minlabel").select("doc_id", "comp")


@query(S.with_(CLUSTERS, "SELECT doc_id, lang, cluster_size FROM clusters WHERE keep"))
def w_dedup_keep(spark, sf_dir):
    return H.keep_one(table(spark, sf_dir, "documents").select("doc_id", "lang"), clusters(spark, sf_dir).drop("lang")).select("doc_id", "lang", "cluster_size")


@query(S.with_(CLUSTERS, "SELECT doc_id, cluster_size FROM clusters JOIN documents d USING (doc_id) QUALIFY row_number() OVER (PARTITION BY comp ORDER BY length(text) DESC, doc_id) = 1"))
def w_dedup_keep_longest(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return H.keep_one(docs, clusters(spark, sf_dir), "longest").select("doc_id", "cluster_size")


@query(S.with_(CLUSTERS, "SELECT lang, cluster_size, count(*) AS n FROM clusters WHERE keep GROUP BY ALL"))
def w_cluster_hist(spark, sf_dir):
    return clusters(spark, sf_dir).where("keep").groupBy("lang", "cluster_size").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT lang, min(doc_id) AS doc_id, count(*) AS n FROM documents GROUP BY lang, text")
def w_dedup_exact(spark, sf_dir):
    return H.exact(table(spark, sf_dir, "documents"))


@query(S.with_(clusters_sql("lang, source"), "SELECT doc_id, comp, cluster_size FROM clusters"))
def w_dedup_per_source(spark, sf_dir):
    return clusters(spark, sf_dir, ("lang", "source")).select("doc_id", "comp", "cluster_size")


@query(S.with_(CLUSTERS, "SELECT doc_id, cluster_size FROM clusters WHERE cluster_size < 4"))
def w_drop_large(spark, sf_dir):
    return H.drop_large(table(spark, sf_dir, "documents").select("doc_id"), clusters(spark, sf_dir), 4).select("doc_id", "cluster_size")


PAIRS = f"""{BANDS},
sz AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
pr AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS k FROM sh x JOIN sh y ON x.lang = y.lang AND x.g = y.g AND x.doc_id < y.doc_id GROUP BY ALL),
pairs AS (SELECT a, b, k / (p.n + q.n - k) AS sim FROM pr JOIN sz p ON p.doc_id = a JOIN sz q ON q.doc_id = b WHERE k / (p.n + q.n - k) >= 0.5)"""


@query(S.with_(PAIRS, "SELECT a, b, round(sim, 6) AS sim FROM pairs"))
def w_jaccard_pairs(spark, sf_dir):
    return H.exact_pairs(table(spark, sf_dir, "documents"), 0.5, CFG).select("a", "b", F.round("sim", 6).alias("sim"))


@query(S.with_(PAIRS, "SELECT floor(round(sim, 9) * 10) / 10 AS bin, count(*) AS n, count(m.a) AS found FROM pairs p LEFT JOIN (SELECT DISTINCT x.doc_id AS a, y.doc_id AS b FROM bands x JOIN bands y USING (band, bkey) WHERE x.doc_id < y.doc_id) m ON p.a = m.a AND p.b = m.b GROUP BY 1"))
def w_lsh_recall(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    return H.recall(H.exact_pairs(docs, 0.5, CFG), bands(spark, sf_dir))
