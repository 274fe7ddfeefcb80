"""Markdown tables of the experiment workloads: ``python -m drstore.plans.report SF_DIR > RESULTS.md``."""

from __future__ import annotations

import os
import sys
import tempfile

from pyspark.sql import SparkSession

from . import queries, workloads

TITLES = {
    "w02_factor_grid_pages": "Factor lengths and unused dictionary, pages",
    "w03_factor_grid_documents": "Factor lengths and unused dictionary, documents",
    "w05_codecs_pages": "Pair codecs, pages in natural order",
    "w06_codecs_pages_url_order": "Pair codecs, pages in URL order",
    "w09_codecs_documents": "Pair codecs, documents",
    "w05_codecs_pages_published_classes": "Pair codecs, pages, the published ratio classes",
    "w07_blocks_pages": "Blocked stores, pages in natural order",
    "w08_blocks_pages_url_order": "Blocked stores, pages in URL order",
    "w10_blocks_documents": "Blocked stores, documents",
    "w11_prefix_dictionaries": "Dictionaries from prefixes, documents, ZZ",
    "w14_appends": "Appended documents",
    "w15_stream_gain": "Bytes by stream and code, documents",
    "w16_equal_size": "Stores of closest size, pages",
    "w18_large_window": "Large windows, documents",
    "w19_two_pass": "Host clusters in two passes, pages",
    "w20_pruning_passes": "Pruning the dictionary, documents",
    "w21_integer_codes": "Length codes, documents",
    "w22_order_independence": "Order of documents and kind of dictionary, pages, ZZ",
    "w23_ratio_of_other_collections": "Other collections, UV",
    "w25_copies_by_distance": "Exact copies by distance, documents, ZV",
    "w26_speed_by_size": "Factors by size of document",
    "huffman_costs": "Huffman codes, documents",
    "dense_pair_and_phrase_costs": "Dense codes, documents",
    "measure_position_skew": "Positions inside documents and overall",
    "measure_foreign_bytes": "Matched bytes from other documents",
    "measure_build_time": "Building and encoding, documents",
}


def table(rows: list[dict]) -> str:
    names = list(rows[0])
    cell = lambda v: f"{v:.2f}" if isinstance(v, float) else str(v)
    return "\n".join(["| " + " | ".join(names) + " |", "|" + "---|" * len(names), *("| " + " | ".join(cell(r[n]) for n in names) + " |" for r in rows)])


def main(sf: str) -> None:
    root = tempfile.mkdtemp(prefix="drstore-report-")
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "6g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").config("spark.checkpoint.dir", f"file://{root}").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    print(f"# Results on {os.path.basename(sf.rstrip('/'))}\n")
    for name, title in TITLES.items():
        rows = [r.asDict() for r in queries.QUERIES[name](spark, sf).collect()]
        print(f"## {title} (`{name}`)\n\n{table(rows)}\n")
    print("## Documents a second, whole runs with scheduling (local[8], 100,000 requests, documents, 4 % dictionary)\n")
    print(table([{"store": s, "access": a, "docs_per_second": round(v)} for s, a, v in workloads.speeds(spark, sf, "documents")]))
    spark.stop()
    import shutil

    shutil.rmtree(root, ignore_errors=True)


if __name__ == "__main__":
    main(sys.argv[1])
