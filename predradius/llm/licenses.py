"""Licence notices found by MinHash bands over overlapping text windows, in SQL functions only.

Templates fall into classes by length. A class has windows half as long again as its longest template, at a stride that makes
some window hold any occurrence whole; from the lowest similarity such a window can have to a template that it holds to
`containment`, the number of one-row bands follows that retrieves the template with probability 1 - `miss`. Every
retrieved template is then verified by the exact share of its word shingles that the window holds.

A band agrees only if the window holds the template's minimal shingle, so windows that hold no shingle of any template
are passed over before their bands are computed; nothing is lost by that.

Edge cases: null, empty and short texts have no shingles and no notice; a template of fewer than
`shingle` words has its whole word sequence as one shingle and is met in windows of that many words, one without words is an error; rows that repeat an id
are reported once; rows without an id are reported under null; an empty table gives no notices. Texts are read whole.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import shared_table
from .windows import let, plain_words, window_hashes

# Usual notices of public licences.
TEMPLATES = {
    "MIT short": "Released under the MIT License.",
    "MIT line": "This software is licensed under the MIT License.",
    "MIT grant": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction",
    "Apache short": "Licensed under the Apache License, Version 2.0.",
    "Apache header": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at",
    "GPL 3 short": "This work is licensed under the GNU General Public License, version 3.",
    "GPL header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "BSD grant": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "MPL header": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "CC BY-NC short": "Licensed under CC BY-NC 4.0.",
    "CC BY": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "CC BY-SA": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "All rights short": "All rights reserved.",
    "All rights": "All rights reserved. No part of this publication may be reproduced",
}


def classes(templates: dict[str, str], shingle: int, containment: float, miss: float) -> list[dict]:
    """Per class of template lengths: names, words of a shingle, window width in words, stride, and bands."""
    import re

    lengths = {name: len(re.findall(r"[^\W_]+", text)) for name, text in templates.items()}
    if empty := [name for name, n in lengths.items() if not n]:
        raise ValueError(f"templates without words: {empty}")
    found: dict[tuple[int, int], list[str]] = {}
    for name, n in lengths.items():
        k = min(n, shingle)
        found.setdefault((k, math.ceil(math.log(n / k, 1.5))), []).append(name)
    out = []
    for (k, _), names in found.items():
        longest, shortest = max(lengths[x] for x in names), min(lengths[x] for x in names)
        width = max(longest + 2, math.ceil(1.5 * longest))
        t, w = shortest - k + 1, width - k + 1
        lowest = containment * t / (w + t - containment * t)
        out.append({"names": names, "shingle": k, "width": width, "stride": width - longest + 1, "bands": math.ceil(math.log(miss) / math.log(1 - lowest))})
    return out


def overlapping(shingles: Column, inside: int, stride: int) -> Column:
    """first_word and distinct shingles of every window of `inside` shingles."""
    def windows(own: Column) -> Column:
        at = F.sequence(F.lit(0), F.greatest(F.size(own) - 1, F.lit(0)), F.lit(stride))
        return F.transform(at, lambda i: F.struct(i.alias("first_word"), F.array_distinct(F.slice(own, i + 1, inside)).alias("window_set")))

    return let(shingles, windows)


def notices(docs: DataFrame, templates: dict[str, str] | None = None, shingle: int = 5, containment: float = 0.8, miss: float = 1e-4,
            id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, template, containment (the best), first_word (of the first window), n_windows of each notice found."""
    spark = docs.sparkSession
    templates = TEMPLATES if templates is None else templates
    plans = classes(templates, shingle, containment, miss)
    sizes = sorted({p["shingle"] for p in plans}) or [shingle]
    known = spark.createDataFrame([(k, name, templates[name], p["shingle"]) for k, p in enumerate(plans) for name in p["names"]], "class int, template string, t string, shingle int")
    of_size = reduce(lambda rest, n: F.when(F.col("shingle") == n, window_hashes(plain_words(F.col("t")), n)).otherwise(rest), sizes, F.array().cast("array<bigint>"))
    known = known.select("class", "template", "shingle", F.array_distinct(of_size).alias("template_set"))
    # As many values as the templates have shingles, whatever the documents.
    every = {n: set() for n in sizes}
    for r in known.select("shingle", "template_set").collect():
        every[r[0]].update(r[1])
    wanted = {n: F.array(*(F.lit(v).cast("long") for v in sorted(own))) if own else F.array().cast("array<bigint>") for n, own in every.items()}
    shingles = let(plain_words(F.col(text_col)), lambda own: F.struct(*(window_hashes(own, n).alias(f"s{n}") for n in sizes)))
    words = docs.select(F.col(id_col).cast("long").alias("doc_id"), shingles.alias("s")).select("doc_id", "s.*")
    # Few documents; every class of templates reads them.
    near = shared_table(words.filter(reduce(Column.__or__, (F.arrays_overlap(f"s{n}", wanted[n]) for n in sizes))))
    hashes = lambda values, i: F.array_min(F.transform(values, lambda v: F.xxhash64(v, i)))
    bands = lambda values, n: F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.struct(i.alias("band"), hashes(values, i).alias("value")))
    made, keys = [], []
    for k, p in enumerate(plans):
        n = p["shingle"]
        cut = overlapping(F.col(f"s{n}"), p["width"] - n + 1, p["stride"])
        own = near.select("doc_id", F.explode(F.filter(cut, lambda w: F.arrays_overlap(w["window_set"], wanted[n]))).alias("w"))  # noqa: B023
        made.append(own.select("doc_id", F.lit(k).alias("class"), "w.first_word", "w.window_set", F.explode(bands(F.col("w.window_set"), p["bands"])).alias("b")))
        keys.append(known.filter(F.col("class") == k).select("class", "template", "template_set", F.explode(bands(F.col("template_set"), p["bands"])).alias("b")))
    retrieved = reduce(DataFrame.union, made).join(F.broadcast(reduce(DataFrame.union, keys)), ["class", "b"])
    share = F.size(F.array_intersect("template_set", "window_set")) / F.size("template_set")
    exact = retrieved.select("doc_id", "template", "first_word", share.alias("share")).filter(F.col("share") >= containment)
    return exact.groupBy("doc_id", "template").agg(F.max("share").alias("containment"), F.min("first_word").alias("first_word"), F.countDistinct("first_word").alias("n_windows"))
