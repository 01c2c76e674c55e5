"""Columnar entropy coding on Spark: Huffman code bits regrouped by tree node into bitmaps."""
