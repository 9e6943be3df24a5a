"""The registered queries of the corpus operators and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from binflow.llm import licenses, neardup, packing, quality, sharding, simhash, substring, tokens, topk
from binflow.storage import new_folder, table

OVER_LIMIT = 1024


def op1_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def op2_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = tokens.encode(table(spark, sf_dir, "documents"), decode=True)
    return rows.select("doc_id", (F.octet_length("tokens") / 4).cast("bigint").alias("n_tokens"), F.sha2("tokens", 256).alias("ids_sha256"), F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"))


def op3_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(table(spark, sf_dir, "embeddings"))


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    store = sharding.shard_table(table(spark, sf_dir, "documents"), new_folder(spark, "shards"), keep_versions=2)
    text = F.coalesce("text", F.lit(""))
    return store.read().select("doc_id", "lang", "source", "n_chars", F.octet_length(text).cast("bigint").alias("n_bytes"), F.md5(text.cast("binary")).alias("text_md5"))


def op5_top_k_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk.top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


def op6_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = simhash.near_duplicates(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op7_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring.repeated_passages(table(spark, sf_dir, "documents"))


def op8_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality.score(docs, quality.train(docs, table(spark, sf_dir, "labels")))


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokens.count_tokens(table(spark, sf_dir, "documents")).withColumn("over_limit", F.col("n_tokens") > OVER_LIMIT)


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.recognise(table(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_best_fit_packing, op2_bpe_round_trip, op3_embedding_near_dedup, op4_sharding, op5_top_k_search, op6_simhash_near_dedup, op7_substring_dedup, op8_quality_classifier, op9_token_counts, op10_license_scan, pipeline)}


def oracle_sql() -> dict[str, str]:
    return {
        "op4_sharding": """
            select doc_id, lang, source, n_chars, cast(octet_length(encode(coalesce(text, ''))) as bigint) as n_bytes, md5(coalesce(text, '')) as text_md5
            from documents""",
        "op5_top_k_search": """
            with v as (select vec_id, list_transform(embedding, lambda x: cast(floor(256 * cast(x as double)) as bigint)) as e from embeddings
                       where embedding is not null and vec_id is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0),
            s as (select q.vec_id as query_id, c.vec_id, cast(list_sum(list_transform(range(1, 65), lambda i: q.e[i] * c.e[i])) as bigint) as score
                  from v q join v c on q.vec_id <> c.vec_id where q.vec_id % 50 = 0),
            r as (select *, row_number() over (partition by query_id order by score desc, vec_id) as rank from s)
            select query_id, cast(rank as int) as rank, vec_id, score from r where rank <= 5""",
        "op10_license_scan": _license_sql(),
    }


def _license_sql() -> str:
    """The tables of sentences and rules, evaluated by DuckDB: own cuts and patterns, no trigger words, rules as sequences of alternatives."""
    known = ", ".join(f"('{s}', '{i}')" for s, i in licenses.SENTENCES.items())
    rows, steps, names = "found", [], []
    for k, (name, parts) in enumerate(licenses.RULES):
        pattern = "".join("(;" + part.rstrip("*").replace(".", "\\.") + ";)" + "?" * part.endswith("*") for part in parts)
        steps.append(f"s{k} as (select * exclude (rest), regexp_matches(rest, '{pattern}') as r{k}, regexp_replace(rest, '{pattern}', '|', 'g') as rest from {rows})")
        names.append(f"case when r{k} then '{name}' end")
        rows = f"s{k}"
    order = ", ".join(f"'{n}'" for n in dict.fromkeys(n for n, _ in licenses.RULES))
    return f"""
        with known(sentence, ident) as (values {known}),
        docs as (select row_number() over () as row, doc_id, lower(coalesce(text, '')) as low from documents),
        parts as (select row, string_split(regexp_replace(regexp_replace(low, '\n[^a-z0-9A-Z]*\n', chr(1), 'g'), '([.]|!|[?])[ \\t\\r\n]+|:[ \\t\\r]*\n', chr(1), 'g'), chr(1)) as parts from docs),
        cut as (select row, unnest(parts) as sentence, generate_subscripts(parts, 1) as place from parts),
        whole as (select row, place, sentence, trim(regexp_replace(sentence, '[^0-9a-z]+', ' ', 'g')) as plain from cut),
        told as (select whole.*, ident from whole left join known on known.sentence = plain),
        lines as (select row, place, unnest(string_split(sentence, chr(10))) as line, generate_subscripts(string_split(sentence, chr(10)), 1) as nth from told where ident is null),
        shown as (select row, place, nth, trim(regexp_replace(line, '[^0-9a-z]+', ' ', 'g')) as plain from lines),
        each as (select row, place, 0 as nth, ident from told where ident is not null
                 union all select row, place, nth, coalesce(ident, case when regexp_matches(plain, '^copyright (c )?[0-9]{{4}}( |$)') then 'copyright' end) from shown left join known on sentence = plain),
        hit as (select row, string_agg(ident, ';' order by place, nth) as sentence_ids,
                       string_agg(';' || ident || ';', '' order by place, nth) filter (where ident <> 'copyright') as rest
                from each where ident is not null group by row),
        found as (select doc_id, coalesce(sentence_ids, '') as sentence_ids, coalesce(rest, '') as rest from docs left join hit using (row)),
        {", ".join(steps)}
        select doc_id, sentence_ids, coalesce(array_to_string(list_filter([{order}], lambda x: list_contains([{", ".join(names)}], x)), ';'), '') as licences,
               cast(len(list_filter(regexp_split_to_array(rest, '[;|]+'), lambda x: x <> '')) as int) as n_unmatched
        from {rows}"""
