"""Where bytes come from: files by range, raw blocks, rendered tables."""
