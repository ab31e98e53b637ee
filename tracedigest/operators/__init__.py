"""The operators of the digest: traces, blocks, filters, indexes, attribution, baselines, measures."""
