"""Training-data operators: secrets, licences, duplicates, decontamination, shards, LM scores, HTML, quality, packing.

Nothing outside this subpackage imports it; ``__spark_entry__`` adds its queries when it can be imported.
"""
