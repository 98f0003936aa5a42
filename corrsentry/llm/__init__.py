"""Training-data operators: sharding, toxicity, substring and near-duplicate removal, quality,
decontamination, media columns, source mixing, URL reputation and WARC revisit resolution.

Nothing outside this subpackage imports it.
"""
