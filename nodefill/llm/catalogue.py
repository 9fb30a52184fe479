"""The registered queries of this subpackage and their SQL."""

from __future__ import annotations

from . import knn_join, media_jpeg, packing, quality, secret_forest, segmentation, suffix_index, url_filter, weighted_minhash, window_dedup

MODULES = (packing, segmentation, quality, suffix_index, knn_join, media_jpeg, weighted_minhash, url_filter, window_dedup, secret_forest)


def queries() -> dict:
    found = {name: getattr(m, name) for m in MODULES for name in dir(m) if name.startswith("op") and name[2].isdigit()}
    return dict(sorted(found.items(), key=lambda x: int(x[0][2:].split("_")[0])))


def oracle_sql() -> dict:
    return {k: v for m in MODULES for k, v in getattr(m, "ORACLES", {}).items()}
