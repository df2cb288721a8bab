"""The operators' registered queries with production parameters, and their SQL where SQL can express them."""

from __future__ import annotations

import os
from collections.abc import Callable
from functools import wraps

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provgraph.llm import chat_format, decontaminate, exact_dedup, language_id, line_dedup, ngram_join, packing, pii, substring_dedup, token_counts
from provgraph.llm.common import small_batches, table

#: Folder of the public tokenizers' files; a parameter, as the files are never copied.
TOKENIZERS = os.environ.get("TOKENIZER_DIR") or os.path.dirname(public_tokenizers.path("word_bpe_49k.json"))
#: Fixed value: the pre-token pattern that belongs to the byte-level vocabulary.
BYTE_PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.language_id(table(spark, sf_dir, "documents"))


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_dedup(table(spark, sf_dir, "documents"))


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    kept = line_dedup.remove_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return kept.select("doc_id", "n_lines", "n_removed", F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


def op4_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), f"{TOKENIZERS}/word_bpe_49k.json")


def op5_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.find_pii(table(spark, sf_dir, "documents"))


def op6_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.ngram_components(table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id")


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text").withColumn("edits", token_counts.stated_edits())
    return token_counts.count_tokens(docs, f"{TOKENIZERS}/byte_bpe_50k.tiktoken", BYTE_PATTERN, "edits")


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.find_items(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op9_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.remove_repeats(table(spark, sf_dir, "documents"))


def op10_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    both = spark.createDataFrame([(-1, 0, "user", "</s>[INST] ok [/INST]"), (-1, 1, "assistant", "</s>[INST] ok [/INST]")], "conv_id long, turn long, role string, text string")
    rows = table(spark, sf_dir, "conversations").select("conv_id", F.col("turn").cast("long").alias("turn"), "role", "text").unionByName(both)
    return chat_format.digest(chat_format.read_back(chat_format.render(chat_format.fold(chat_format.as_events(rows)))))


def _registered(query: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    @wraps(query)
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        small_batches(spark)
        return query(spark, sf_dir)

    return run


_ALL = (op1_language_id, op2_exact_dedup, op3_line_dedup, op4_best_fit_packing, op5_personal_data, op6_ngram_jaccard_join, op7_token_counts, op8_decontamination, op9_substring_dedup, op10_chat_format)
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: _registered(f) for f in _ALL}

_WORDS = r"[^\x20\x09-\x0D]+"
_LOWERED = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def _shingles(name: str, table_: str, key: str) -> str:
    """(key, g): the distinct 5-word shingles of a table's lower-cased texts."""
    return f"""{name}_w AS (SELECT {key}, regexp_extract_all({_LOWERED}, '{_WORDS}') AS w FROM {table_}),
        {name} AS (SELECT DISTINCT {key}, unnest(CASE WHEN len(w) >= 5 THEN list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS g FROM {name}_w)"""


def _escaped(c: str) -> str:
    return rf"regexp_replace(replace({c}, '\', '\b'), '([<\[])(s>|/s>|INST\]|/INST\])', '\1\\\2', 'g')"


ORACLES: dict[str, str] = {
    "op2_exact_dedup": """
        WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
        g AS (SELECT t, max(doc_id) AS keep_id, count(*) AS group_size FROM d GROUP BY t)
        SELECT d.doc_id, g.keep_id, g.group_size, d.doc_id = g.keep_id AS kept, sha256(d.t) AS text_sha256 FROM d JOIN g ON d.t = g.t""",
    "op6_ngram_jaccard_join": f"""
        WITH RECURSIVE {_shingles("s", "documents", "doc_id")},
        n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
        c AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL),
        l AS (SELECT x, y FROM c JOIN n p ON p.doc_id = x JOIN n q ON q.doc_id = y WHERE 100 * k >= 75 * (p.n + q.n - k)),
        r AS (SELECT doc_id AS x, doc_id AS y FROM documents UNION SELECT r.x, l.y FROM r JOIN l ON l.x = r.y)
        SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, m.component_id FROM documents d LEFT JOIN n ON n.doc_id = d.doc_id JOIN (SELECT x, min(y) AS component_id FROM r GROUP BY x) m ON m.x = d.doc_id""",
    "op8_decontamination": f"""
        WITH {_shingles("s", "documents", "doc_id")}, {_shingles("b", "benchmark", "item_id")},
        size AS (SELECT item_id, count(*) AS m FROM b GROUP BY 1),
        hit AS (SELECT doc_id, item_id, count(*) AS k FROM s JOIN b ON s.g = b.g GROUP BY ALL),
        ok AS (SELECT doc_id, hit.item_id, 100 * k // m AS pc FROM hit JOIN size ON size.item_id = hit.item_id WHERE 100 * k >= 75 * m),
        found AS (SELECT doc_id, count(*) AS n_items, string_agg(item_id::VARCHAR, ',' ORDER BY item_id) AS item_ids, max(pc) AS best FROM ok GROUP BY 1)
        SELECT d.doc_id, n_items IS NOT NULL AS contaminated, coalesce(n_items, 0)::BIGINT AS n_items, coalesce(item_ids, '') AS item_ids, coalesce(best, 0)::BIGINT AS best_percent FROM documents d LEFT JOIN found ON found.doc_id = d.doc_id""",
    "op9_substring_dedup": f"""
        WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '{_WORDS}') AS w FROM documents),
        v AS (SELECT doc_id, unnest(range(1, len(w) - 11)) AS i, unnest(list_transform(range(1, len(w) - 11), lambda i: array_to_string(w[i:i + 12], ' '))) AS t FROM w WHERE len(w) >= 13),
        o AS (SELECT doc_id, i, min(doc_id) OVER (PARTITION BY t) AS owner FROM v),
        gone AS (SELECT DISTINCT doc_id, unnest(range(i, i + 13)) AS j FROM o WHERE owner < doc_id),
        g AS (SELECT doc_id, list(j) AS js FROM gone GROUP BY 1),
        k AS (SELECT w.doc_id, len(w) AS n, w, coalesce(js, []) AS js FROM w LEFT JOIN g ON g.doc_id = w.doc_id),
        x AS (SELECT doc_id, n, len(js) AS removed, unnest(w) AS word, unnest(range(1, n + 1)) AS j, js FROM k WHERE n > 0),
        y AS (SELECT x.doc_id, string_agg(word, ' ' ORDER BY x.j) AS kept FROM x LEFT JOIN gone ON gone.doc_id = x.doc_id AND gone.j = x.j WHERE gone.j IS NULL GROUP BY 1)
        SELECT k.doc_id, n::BIGINT AS n_words, len(js)::BIGINT AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM k LEFT JOIN y ON y.doc_id = k.doc_id""",
    "op10_chat_format": f"""
        WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
          UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'),
        f AS (SELECT conv_id, count(*) AS n_turns, string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text) AS turns,
          coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '') AS loss, sum(length({_escaped("role")}) + length({_escaped("text")}) + 20) AS chars FROM c GROUP BY 1)
        SELECT conv_id, n_turns, sha256(turns) AS turns_sha256, length(loss) AS loss_chars, sha256(loss) AS loss_sha256, chars::BIGINT AS formatted_chars FROM f""",
}
