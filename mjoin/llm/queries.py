"""The contract queries opN_<name>: each applies its operator to its whole table."""

from __future__ import annotations

from . import decontaminate, html_wrapper, langid, mixing, ngram_join, phrases, pii, sketch, token_files, toxicity
from .common import load


def vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op1_mix_sources(spark, sf_dir):
    return mixing.mix(load(spark, sf_dir, "documents"))


def op2_html_text(spark, sf_dir):
    return html_wrapper.extract(load(spark, sf_dir, "pages"))


def op3_token_files(spark, sf_dir):
    return token_files.token_table(load(spark, sf_dir, "documents"), vocabulary())


def op4_ngram_join(spark, sf_dir):
    return ngram_join.near_duplicates(load(spark, sf_dir, "documents"))


def op5_toxicity(spark, sf_dir):
    docs = load(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.fit(docs, load(spark, sf_dir, "labels")))


def op6_decontaminate(spark, sf_dir):
    return decontaminate.contamination(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark")).drop("spans")


def op7_repeated_passages(spark, sf_dir):
    return phrases.repeated_passages(load(spark, sf_dir, "documents")).drop("spans")


def op8_personal_data(spark, sf_dir):
    return pii.find_personal_data(load(spark, sf_dir, "documents"), pii.train_field(spark))


def op9_fingerprints(spark, sf_dir):
    return sketch.fingerprints(load(spark, sf_dir, "documents"))


def op10_language_id(spark, sf_dir):
    docs = load(spark, sf_dir, "documents")
    return langid.identify(docs, langid.learn_profiles(docs))


def base_personal_data(spark, sf_dir):
    """What op8 counts by its fixed patterns."""
    return pii.base_counts(load(spark, sf_dir, "documents"))


def edited_texts(spark, sf_dir):
    """What op9 says of the edited texts."""
    return sketch.fingerprints(load(spark, sf_dir, "documents")).select("doc_id", "n_chars", "edited_sha256")


QUERIES = {f.__name__: f for f in (base_personal_data, edited_texts, op1_mix_sources, op2_html_text, op3_token_files, op4_ngram_join, op5_toxicity, op6_decontaminate, op7_repeated_passages, op8_personal_data, op9_fingerprints, op10_language_id)}

ORACLE: dict[str, str] = {
    "base_personal_data": pii.COUNTS_SQL,
    "edited_texts": sketch.EDITS_SQL,
    "op1_mix_sources": mixing.MIX_SQL,
    "op6_decontaminate": decontaminate.CONTAMINATION_SQL,
    "op7_repeated_passages": phrases.PASSAGES_SQL,
}
