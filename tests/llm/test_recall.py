"""How many of a document's best neighbours in the whole table share its shard."""

import numpy as np

from freqsketch.llm import packing
from freqsketch.llm.tokens import encoder, tokenizer_path


def recall(spark, folder, shard_docs, queries=400, best=8):
    """(shards, all, strong): shares of the ``best`` neighbours by brute force over all documents, and
    of those of them that score half as much as the document itself or more."""
    docs = spark.read.parquet(f"{folder}/documents.parquet").select("doc_id", "text")
    packed = packing.pack_documents(docs, "text", "doc_id", tokenizer_path(), ids_too=False, shard_docs=shard_docs)
    shard = {r.doc_id: r.sequence_id >> 32 for r in packed.select("doc_id", "sequence_id").collect()}
    rows = docs.collect()
    of = np.array([shard[r.doc_id] for r in rows])
    ids, n = encoder(tokenizer_path()).encode([r.text or "" for r in rows])
    marks = packing._word_marks(tokenizer_path())
    ends = np.concatenate([[0], np.cumsum(n)])
    _, term, _ = packing.document_terms(ids, n, marks)
    counts = np.bincount(term, minlength=1 << packing.TERM_BITS)
    idf = np.log1p((len(n) - counts + 0.5) / (counts + 0.5))
    index = packing.ShardIndex(ids, n, marks, idf, float(n.mean() + 1))
    assert ends[-1] == len(ids)
    hits, strong = [], []
    for doc in np.random.default_rng(0).choice(len(n), min(queries, len(n)), replace=False):
        score = index.scores(doc)
        own, score[doc] = score[doc], -1
        top = np.argsort(-score)[:best]
        hits += (of[top] == of[doc]).tolist()
        strong += (of[top] == of[doc])[score[top] >= own / 2].tolist()
    return len(set(of.tolist())), float(np.mean(hits)), float(np.mean(strong))


def test_like_documents_share_a_shard(spark, sf):
    shards, every, strong = recall(spark, sf.replace("0.001", "0.01"), 128)
    assert shards >= 8
    # by chance both were 1 / shards
    assert strong > 0.7 and every > 1.2 / shards
