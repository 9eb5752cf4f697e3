"""Training-data operators: dedup, tokenising, formatting, classifying, extraction and packing.

Nothing outside this subpackage imports it; ``__spark_entry__`` adds its queries when it is present.
"""
