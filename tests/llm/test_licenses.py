"""Texts with several notices: each is found, however many stand in one text."""

from spectral_frames.llm import licenses

NOTICES = {
    "mit": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software. Released under the MIT License.",
    "bsd": "Redistribution and use in source and binary forms, with or without modification, are permitted.",
    "apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "mpl-2.0": "Mozilla Public License, version 2.0",
    "isc": "Permission to use, copy, modify, and/or distribute this software for any purpose",
}


def labels(spark, texts):
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    return [set(r["labels"].split(",")) - {""} for r in licenses.scan(docs).orderBy("doc_id").collect()]


def test_five_notices_in_one_text(spark):
    # rows about other things give the words of the notices a weight
    prose = ["plain words about the weather and the sea"] * 40
    found = labels(spark, [" and more text. ".join(NOTICES.values()), *NOTICES.values(), *prose])
    for one, expected in zip(found[1:6], NOTICES, strict=True):
        assert expected in one
    assert found[0] == set().union(*found[1:6]) and not any(found[6:])


def test_every_template_in_one_text(spark):
    text = ". unrelated words. ".join(notice for _, notice, _ in licenses.TEMPLATES)
    assert {label for label, _, _ in licenses.TEMPLATES} <= labels(spark, [text, *["plain words"] * 20])[0]
