"""Training-data operators (text clean-up, dedup, scans, codecs). Nothing outside this subpackage imports it."""
