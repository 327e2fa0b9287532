"""The ten text operators over their whole tables, and the pipeline, as registered queries."""

from __future__ import annotations

import corpus_pipeline
import public_tokenizers

from edgecsr.llm import dart_minhash, exact_topk, hnsw, log_bilinear, quality, toxicity
from edgecsr.llm.bpe_transducer import encode_documents
from edgecsr.llm.common import read
from edgecsr.llm.html_extract import extract_pages
from edgecsr.llm.packing import added_tokens, pack
from edgecsr.llm.suffix_array import remove_repeats


def op1_toxicity_chain(spark, sf_dir):
    docs = read(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.train(docs, read(spark, sf_dir, "labels")))


def op2_dart_minhash(spark, sf_dir):
    return dart_minhash.classes(read(spark, sf_dir, "documents"))


def op3_quality_cotraining(spark, sf_dir):
    docs = read(spark, sf_dir, "documents")
    return quality.score(docs, quality.train(docs, read(spark, sf_dir, "labels")))


def op4_suffix_array(spark, sf_dir):
    return remove_repeats(read(spark, sf_dir, "documents"))


def op5_html_tree_scoring(spark, sf_dir):
    return extract_pages(read(spark, sf_dir, "pages"))


def op6_log_bilinear(spark, sf_dir):
    return log_bilinear.score(read(spark, sf_dir, "documents"))


def op7_byte_bpe(spark, sf_dir):
    return encode_documents(read(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)


def op8_complement_packing(spark, sf_dir):
    return pack(read(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"), added=added_tokens(public_tokenizers.path("byte_bpe_50k.json")))


def op9_sorted_list_topk(spark, sf_dir):
    return exact_topk.search(read(spark, sf_dir, "embeddings"))


def op10_hnsw(spark, sf_dir):
    return hnsw.nearest(read(spark, sf_dir, "embeddings"))


def pipeline(spark, sf_dir):
    return corpus_pipeline.run(spark, sf_dir)


def queries():
    return {
        "op1_toxicity_chain": op1_toxicity_chain,
        "op2_dart_minhash": op2_dart_minhash,
        "op3_quality_cotraining": op3_quality_cotraining,
        "op4_suffix_array": op4_suffix_array,
        "op5_html_tree_scoring": op5_html_tree_scoring,
        "op6_log_bilinear": op6_log_bilinear,
        "op7_byte_bpe": op7_byte_bpe,
        "op8_complement_packing": op8_complement_packing,
        "op9_sorted_list_topk": op9_sorted_list_topk,
        "op10_hnsw": op10_hnsw,
        "pipeline": pipeline,
    }


def oracle_sql():
    return {}
