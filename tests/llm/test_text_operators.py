"""Per-row operators against brute force, round trips and odd rows."""

import base64
import bz2
import gzip
import hashlib
import lzma
import random
import zlib
import re
import zlib

import numpy as np
import pandas as pd
import public_tokenizers
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from setsync.llm import chat, licenses, packing, piecewise, secrets, shared, simhash, tokens, toxicity

ODD = "doc_id long, text string, lang string, source string, n_chars long, size int, fp string"
ODD_ROWS = [
    (1, None, None, None, None, 1, "x"), (2, "", "en", "a", 0, 2, None), (3, " \t\n ", "en", "a", 4, 3, "y"),
    (4, "same words here", "en", "a", 15, 4, "z"), (4, "same words here", "en", "a", 15, 4, "z"),
    (None, "no id at all", "de", None, 12, 5, "w"), (6, "long " * 9000, "fr", "b", 45000, 6, "v"),
]


def odd(spark, rows=ODD_ROWS):
    return spark.createDataFrame(rows, ODD)


def texts_of(spark, folder):
    return [r.text for r in shared.table(spark, folder, "documents").select("text").collect()]


def test_secret_base_findings_match_the_patterns(spark, smoke):
    text = "x token = \"abcDEF12\" secret=token = abcdefgh AKIA" + "Q" * 16 + " AKIA1 é" + "0af" * 9 + " PASSWD:'zzzzzz' api_key=12345"
    for t in [text, *texts_of(spark, smoke)]:
        want = [(m.start(), 0, m.end()) for m in secrets.ASSIGN.finditer(t) if len(m[2]) >= 6]
        want += [(m.start(), 1, m.end()) for m in re.finditer("AKIA[A-Z0-9]+", t) if len(m[0]) >= 20]
        want += [(m.start(), 2, m.end()) for m in re.finditer("[0-9a-f]+", t) if len(m[0]) >= 24]
        assert secrets.find_secrets(t)[0] == sorted(want)


def test_secrets_inside_nested_layers_map_to_the_outer_text():
    plain = "password=hunter2secret"
    wrapped = {
        "url": "".join(f"%{b:02X}" for b in plain.encode()),
        "unicode": "".join(f"\\u{ord(c):04x}" for c in plain),
        "entity": "".join(f"&#{ord(c)};" for c in plain),
        "base64": base64.b64encode(plain.encode()).decode(),
        "gzip": base64.b64encode(gzip.compress(plain.encode())).decode(),
    }
    wrapped["twice"] = base64.b64encode(wrapped["url"].encode()).decode()
    wrapped["thrice"] = base64.b64encode(gzip.compress(wrapped["twice"].encode())).decode()
    for kind, body in wrapped.items():
        text = f"before é {body} after"
        base, every, layers, unopened = secrets.find_secrets(text)
        inner = [(s, e) for s, k, e in every if k == 0]
        assert inner and all(9 <= s < e <= 9 + len(body) for s, e in inner), kind
        assert set(base) <= set(every) and layers > 1 and not unopened
        assert secrets.find_secrets(secrets.masked(text, every))[1] == []


def test_secret_layers_that_repeat_end():
    assert secrets.find_secrets("%2525252525 " * 50)[2] < 10


def test_secrets_in_layers_that_are_odd_misaligned_wrapped_or_long(monkeypatch):
    plain = "password=hunter2secret"
    b64 = lambda b: base64.b64encode(b).decode()
    noise = random.Random(1).randbytes(300)
    mime = base64.encodebytes(gzip.compress(noise + plain.encode())).decode().strip()
    cases = {
        "nbsp": b64(f"mot\u00a0de passe {plain}".encode()), "nul": b64(b"a\0b " + plain.encode()), "bom": b64(("\ufeff" + plain).encode()),
        "not utf-8": b64(b"\xe9t\xe9 " + plain.encode()), "gzip with nbsp": b64(gzip.compress(f"\u3000{plain}".encode())),
        "url not utf-8": "%E9" + "".join(f"%{b:02X}" for b in plain.encode()),
        "path": "/files/" + b64(plain.encode()), "dash": "id-" + b64(plain.encode()), "letters": "abcd1" + b64(plain.encode()).rstrip("="),
        "path gzip": "/f/" + b64(gzip.compress(plain.encode())), "mod 1": b64(plain.encode() + b"xx").rstrip("=") + "A",
        "mime": mime, "mime crlf": mime.replace("\n", "\r\n"), "wrapped": "cGFz\n" + b64(plain.encode())[4:],
        "members": b64(gzip.compress(b"first ") + gzip.compress(plain.encode())), "straddling": b64(gzip.compress(plain[:12].encode()) + gzip.compress(plain[12:].encode())),
        "bz2 members": b64(bz2.compress(b"first ") + bz2.compress(plain.encode())), "xz members": b64(lzma.compress(b"first ") + lzma.compress(plain.encode())),
        "within": b64(b"\x00\x01head" + zlib.compress(plain.encode())),
    }
    for kind, body in cases.items():
        text = f"before é {body} after"
        every = secrets.find_secrets(text)[1]
        inner = [(s, e) for s, k, e in every if k == 0]
        assert inner and all(9 <= s < e <= 9 + len(body) for s, e in inner), kind
        assert secrets.find_secrets(secrets.masked(text, every))[1] == [], kind
    monkeypatch.setattr(secrets, "INFLATE", 1 << 20)
    monkeypatch.setattr(secrets, "OVERLAP", 1 << 12)
    for pack in (gzip.compress, bz2.compress, lzma.compress):
        for where in ((1 << 20) - 9, (1 << 21) - 4096 - 5, 5 << 20):
            assert any(k == 0 for _, k, _ in secrets.find_secrets("x " + b64(pack(b"." * where + b" " + plain.encode() + b" " * (1 << 20))))[1])


def test_every_copy_of_a_wrapped_secret_is_found():
    rng = random.Random(5)
    b64 = lambda b: base64.b64encode(b).decode()
    wraps = [
        lambda t: "".join(f"%{b:02X}" for b in t.encode()), lambda t: "".join(f"\\u{ord(c):04x}" for c in t), lambda t: "".join(f"&#{ord(c)};" for c in t),
        lambda t: b64(t.encode()), lambda t: b64(gzip.compress(t.encode())), lambda t: b64(bz2.compress(t.encode())), lambda t: b64(lzma.compress(t.encode())),
    ]
    for case in range(60):
        plain = f"token = {rng.getrandbits(60):x}zz{case}"
        body = plain
        for _ in range(rng.randrange(1, 4)):
            body = rng.choice(wraps)(body)
        other = wraps[3](f"password={rng.getrandbits(60):x}".encode().decode())
        text, places = "start", []
        for part in (body, other, body, body, other):
            text += rng.choice([" ", "\n\n", " é, "])
            places.append((len(text), len(text) + len(part)))
            text += part
        every = secrets.find_secrets(text)[1]
        for a, b in places:
            assert any(a <= s < e <= b for s, _, e in every), (case, a, b)
        left = secrets.masked(text, every)
        assert body not in left and other not in left and secrets.find_secrets(left)[1] == []
    strong = base64.b64encode(lzma.compress(b"password=hunter2secret" + rng.randbytes(2000), preset=9)).decode()
    assert any(k == 0 for _, k, _ in secrets.find_secrets(strong)[1])
    damaged = base64.b64encode(gzip.compress(b"password=hunter2secret " * 3)[:-9]).decode()
    assert any(k == 0 for _, k, _ in secrets.find_secrets(damaged)[1])


def test_merged_ids_equal_the_library(spark, smoke):
    rng = random.Random(8)
    for name in ("word_bpe_49k.json", "byte_bpe_50k.json"):
        path = public_tokenizers.path(name)
        pieces = {"".join(rng.choices("abcdefghiklmnorstu", k=rng.randrange(1, 30))) for _ in range(4000)}
        pieces |= {"".join(rng.choices("aé日ß😀1-'", k=rng.randrange(1, 12))) for _ in range(1000)} | {"a" * 200, "ab" * 31, "x"}
        pieces, model = sorted(pieces), tokens.load(path)[0].model
        want = [np.array([t.id for t in model.tokenize(tokens.as_letters(p))], "<u4").tobytes() for p in pieces]
        assert tokens.Merger(path).ids(pieces) == want


def test_caches_that_turn_over_change_no_id(spark, smoke, monkeypatch):
    path = public_tokenizers.path("word_bpe_49k.json")
    texts = texts_of(spark, smoke)[:60] + [None, "", " "]
    column = pa.array(["skipped", *texts], pa.string()).slice(1)
    want = list(tokens.ChunkIds(path).encode_column(column))
    assert want == [tokens.ChunkIds(path).encode(t) for t in texts]
    monkeypatch.setattr(tokens, "BLOCK_BYTES", 500)
    small = tokens.ChunkIds(path)
    small.chunks, small.pieces = tokens.Recent(50), tokens.Recent(20)
    assert list(small.encode_column(column)) == want


def test_arrow_splits_where_python_does():
    every = [f"a{chr(c)}b" for c in range(0x110000) if not 0xD800 <= c < 0xE000 and not 0x1C <= c <= 0x1F]
    got = pc.utf8_split_whitespace(pa.array(every)).to_pylist()
    assert [x for x, y in zip(every, got) if x.split() != y] == []


def test_chat_round_trip_and_loss(spark):
    words = ["<|im_end|>", "\\", "<|", "<\\|", "\n", "ok", "é", "", "\\n", "<"]
    rng = random.Random(3)
    rows = [(c, t, rng.choice(["user", "assistant", "sys\ntem", None]), "".join(rng.choices(words, k=5)) if rng.random() > 0.1 else None) for c in range(30) for t in range(rng.randrange(1, 6))]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("valid", F.lit(1))
    got = {r.conv_id: r for r in chat.read_chats(chat.format_chats(turns)).collect()}
    for c in {r[0] for r in rows}:
        own = [(r[2] or "", r[3] or "") for r in rows if r[0] == c]
        assert got[c].turns_sha256 == hashlib.sha256("".join(f"{a}\n{b}\n" for a, b in own).encode()).hexdigest()
        loss = "".join(b for a, b in own if a == "assistant")
        assert (got[c].n_turns, got[c].loss_chars) == (len(own), len(loss))
        assert got[c].loss_sha256 == hashlib.sha256(loss.encode()).hexdigest()


def test_chat_machine_marks_bad_orders(spark):
    rows = [(1, 0, "user", "a"), (1, 1, "assistant", "b"), (2, 0, "assistant", "a"), (3, 0, "user", "a"), (3, 1, "user", "b")]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    assert {r.conv_id: r.valid for r in chat.read_chats(chat.format_chats(turns)).collect()} == {1: True, 2: False, 3: False}
    assert chat.read_chats(chat.format_chats(turns.limit(0))).count() == 0


def test_token_counts_equal_the_library(spark, smoke):
    path = public_tokenizers.path("byte_bpe_50k.json")
    library = Tokenizer.from_file(path)
    extra = ["a<|endoftext|> b", "  x   \n\n y\t", "  z\x1c1", "don't we'LL 12345 ½²", "日本語 한국 😀‍💻", "é İΣς", "\x85 a\x0b"]
    lengths = tokens.Lengths(path, {})
    for t in extra + texts_of(spark, smoke)[:100]:
        assert lengths.count(t) == len(library.encode(t, add_special_tokens=False).ids), repr(t[:40])
    counted = {r.doc_id: r.n for r in odd(spark).select("doc_id", tokens.token_counts(odd(spark), path).alias("n")).collect()}
    assert counted[1] == counted[2] == 0 and counted[6] == len(library.encode("long " * 9000).ids)


def test_chunk_ids_equal_the_library(spark, smoke):
    path = public_tokenizers.path("word_bpe_49k.json")
    library, own = Tokenizer.from_file(path), tokens.ChunkIds(path)
    extra = ["a<|endoftext|> b", "İstanbul ΣΑΣ Σ ofﬁce don'T we'll", "  z\x1c1 \x85b", "éé 1234 ²½", "日本語 한국 😀", " ́a", "ͅ"]
    for t in extra + texts_of(spark, smoke)[:100]:
        assert own.encode(t) == np.array(library.encode(t, add_special_tokens=False).ids, "<u4").tobytes(), repr(t[:40])


def brute_print(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    words = re.findall(r"[^\x20\x09-\x0D]+", low)
    h = [xxhash.xxh64_intdigest(" ".join(words[i : i + 4]).encode(), 42) for i in range(max(1, len(words) - 3))] if words else []
    return sum(1 << b for b in range(64) if h and 2 * sum(x >> b & 1 for x in h) > len(h))


def test_simhash_fingerprints(spark, smoke):
    for t in [None, "", " ", "One", "a b c d", "É A B c d e f", *texts_of(spark, smoke)[:60]]:
        assert simhash.fingerprint(t) == brute_print(t)


def test_piecewise_fingerprints():
    rng = random.Random(1)
    text = "".join(rng.choices("abcdefgh éß", k=6000))
    assert piecewise.likeness(piecewise.fingerprint(text), piecewise.fingerprint(text)) == 1
    assert piecewise.likeness(piecewise.fingerprint(text), piecewise.fingerprint("intro " + text[:3000] + "!" + text[3000:])) > 0.8
    other = "".join(rng.choices("abcdefgh éß", k=6000))
    assert piecewise.likeness(piecewise.fingerprint(text), piecewise.fingerprint(other)) < 0.2
    assert piecewise.fingerprint(None) == piecewise.fingerprint("") == "3::"
    assert piecewise.common_letters("abcbdab", "bdcaba") == 4


def test_next_document_wraps_and_survives_odd_rows(spark):
    rows = [(k, f"text {k} " * (k % 5 + 1)) for k in range(0, 200, 3)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    for buckets in (1, 7, 64):
        got = {r.doc_id: r for r in piecewise.fingerprints_with_edit(docs, buckets=buckets).collect()}
        assert len(got) == len(rows)
        for k, (i, t) in enumerate(rows):
            want = piecewise.edited(t, rows[(k + 1) % len(rows)][1])
            assert got[i].edited_sha256 == hashlib.sha256(want.encode()).hexdigest()
    assert piecewise.fingerprints_with_edit(odd(spark), buckets=3).count() == len(ODD_ROWS)
    assert piecewise.fingerprints_with_edit(docs.limit(0)).count() == 0
    assert piecewise.fingerprints_with_edit(docs.where("doc_id = 3")).count() == 1


def test_licence_sentences_and_rules():
    names = lambda t: licenses.scan(t)[2]
    assert names("Words.\nReleased under the MIT License.\nMore") == "MIT"
    assert names("This work is licensed under the GNU General Public License, version 3.") == "GPL-3"
    assert names("Licensed under the Apache License, Version 2.0.") == "Apache-2.0"
    assert names("So. Licensed under CC BY-NC 4.0. And so") == "CC-BY-NC-4.0"
    assert names("// SPDX-License-Identifier: BSD-3-Clause") == "bsd-3-clause"
    mit = "Copyright (c) 2020 Someone. Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal. The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. The software is provided \"as is\", without warranty of any kind, express or implied."
    assert names(mit) == "MIT" and licenses.scan(mit)[0] == 4
    assert licenses.scan("All rights reserved.")[3] == "all-rights"
    assert licenses.scan(None) == licenses.scan("nothing of the kind") == (0, "", "", "", "")
    spans = licenses.scan("Ah. Released under the MIT License. Oh")[4]
    assert spans.startswith("released-mit:")


def test_licences_against_plain_search(spark, smoke):
    lines = {"MIT": "Released under the MIT License.", "GPL-3": "This work is licensed under the GNU General Public License, version 3.", "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0.", "Apache-2.0": "Licensed under the Apache License, Version 2.0."}
    for t in texts_of(spark, smoke):
        want = sorted(n for n, line in lines.items() for _ in range(t.split("\n").count(line)))
        assert sorted(x for x in licenses.scan(t)[2].split(",") if x) == want

LICENCE_TEXTS = {
    "MIT": """The MIT License (MIT)

Copyright (c) 2020 Some One

Permission is hereby granted, free of charge, to any person obtaining a copy
of this software and associated documentation files (the "Software"), to deal
in the Software without restriction, including without limitation the rights
to use, copy, modify, merge, publish, distribute, sublicense, and/or sell
copies of the Software, and to permit persons to whom the Software is
furnished to do so, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all
copies or substantial portions of the Software.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR
IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY,
FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE
AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER
LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM,
OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE
SOFTWARE.""",
    "BSD-3-Clause": """Copyright (c) 2020, Some One, Inc.
All rights reserved.

Redistribution and use in source and binary forms, with or without
modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice, this
   list of conditions and the following disclaimer.

2. Redistributions in binary form must reproduce the above copyright notice,
   this list of conditions and the following disclaimer in the documentation
   and/or other materials provided with the distribution.

3. Neither the name of the copyright holder nor the names of its
   contributors may be used to endorse or promote products derived from
   this software without specific prior written permission.

THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS"
AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE
IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE
DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE
FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL
DAMAGES.""",
    "Apache-2.0": """Copyright 2020 Some One

Licensed under the Apache License, Version 2.0 (the "License");
you may not use this file except in compliance with the License.
You may obtain a copy of the License at

    http://www.apache.org/licenses/LICENSE-2.0

Unless required by applicable law or agreed to in writing, software
distributed under the License is distributed on an "AS IS" BASIS,
WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.
See the License for the specific language governing permissions and
limitations under the License.""",
    "GPL-2": """Copyright (C) 2020  Some One

This program is free software; you can redistribute it and/or modify
it under the terms of the GNU General Public License as published by
the Free Software Foundation; either version 2 of the License, or
(at your option) any later version.

This program is distributed in the hope that it will be useful,
but WITHOUT ANY WARRANTY; without even the implied warranty of
MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.  See the
GNU General Public License for more details.

You should have received a copy of the GNU General Public License along
with this program; if not, write to the Free Software Foundation, Inc.,
51 Franklin Street, Fifth Floor, Boston, MA 02110-1301 USA.""",
    "LGPL-2.1": """This library is free software; you can redistribute it and/or
modify it under the terms of the GNU Lesser General Public
License as published by the Free Software Foundation; either
version 2.1 of the License, or (at your option) any later version.

This library is distributed in the hope that it will be useful,
but WITHOUT ANY WARRANTY; without even the implied warranty of
MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.

You should have received a copy of the GNU Lesser General Public
License along with this library.""",
    "MPL-2.0": """This Source Code Form is subject to the terms of the Mozilla Public
License, v. 2.0. If a copy of the MPL was not distributed with this
file, You can obtain one at http://mozilla.org/MPL/2.0/.""",
}
LICENCE_TEXTS["GPL-3"] = LICENCE_TEXTS["GPL-2"].replace("software; you", "software: you").replace("version 2", "version 3")
LICENCE_TEXTS["BSD-2-Clause"] = re.sub(r"3\. Neither.*?\n\n", "", LICENCE_TEXTS["BSD-3-Clause"], flags=re.S)


def test_licences_wrapped_over_lines():
    for want, text in LICENCE_TEXTS.items():
        plain_ids = licenses.scan(text)[1]
        for mark, close in (("", ""), ("# ", ""), ("// ", ""), (" * ", ""), ("; ", ""), ("| ", " |")):
            lines = "\n".join((mark + line + close).rstrip() for line in text.split("\n"))
            wrapped = f"/*\n{lines}\n */\ncode()"
            n, ids, names, left, spans = licenses.scan(wrapped)
            assert (names, left, ids) == (want, "", plain_ids), (want, mark)
            for span in spans.split(","):
                name, s, e = span.split(":")
                assert 0 <= int(s) < int(e) <= len(wrapped)
        unwrapped = "\n".join(" ".join(part.split()) for part in text.split("\n\n"))
        assert licenses.scan(unwrapped)[2] == want, want
    s, e = map(int, licenses.scan(LICENCE_TEXTS["MPL-2.0"])[4].split(":")[1:])
    assert LICENCE_TEXTS["MPL-2.0"][s:e].endswith("v. 2.0.") and s == 0
    assert licenses.scan("the rights of the\ncopyright holders are kept")[0] == 0
    assert licenses.scan("Copyright 2020 A\nCopyright 2021 B\n\nAll rights\nreserved.")[1] == "copyright,copyright,all-rights"


def test_toxicity_learns_words_and_stems():
    rng = random.Random(5)
    filler = ["alpha", "beta", "gamma", "delta", "epsilon", "zeta", "eta", "theta"]
    texts, labels = [], []
    for k in range(400):
        words = rng.choices(filler, k=rng.randrange(5, 60))
        if k % 4 == 0:
            words[rng.randrange(len(words))] = rng.choice(["awful", f"vequ{rng.randrange(10**6)}"])
        texts.append(" ".join(words))
        labels.append(int(k % 4 == 0))
    model = toxicity.fit(texts[:300], labels[:300])
    scores = toxicity.Scorer(model).scores([*texts[300:], None, ""])
    assert np.mean((scores[:100] >= 0.5) == np.array(labels[300:])) > 0.95
    assert ((scores >= 0) & (scores <= 1)).all() and scores[-1] == scores[-2]
    alone = toxicity.Scorer(model).scores(texts[300:310])
    assert np.allclose(alone, scores[:10])
    assert toxicity.Scorer(toxicity.fit([], [])).scores(["a"])[0] == 0
    assert toxicity.Scorer(toxicity.fit(["a"], [1])).scores(["a"])[0] == 1


def test_toxicity_ignores_held_out_labels(spark):
    labels = spark.createDataFrame([(k, k % 2) for k in range(50)] + [(None, 1), (60, None)], "doc_id long, toxic int")
    docs = spark.createDataFrame([(k, f"t{k}") for k in range(61)], "doc_id long, text string")
    import zlib

    ids = {r.doc_id for r in toxicity.labelled_sample(docs, labels).collect()}
    assert ids == {k for k in range(50) if zlib.crc32(str(k).encode()) % 5}


def test_best_fit_against_a_plain_list():
    rng = random.Random(9)
    fit = packing.BestFit(room=50, open_bins=4)
    bins, opened = {}, 0
    for _ in range(2000):
        n = rng.randrange(1, 51)
        fits = sorted((50 - used, k) for k, used in bins.items() if 50 - used >= n)
        number, offset = fit.place(n)
        if fits:
            assert 50 - offset == fits[0][0]
        else:
            assert offset == 0
            if len(bins) >= 4:
                bins.pop(max(bins, key=lambda k: (bins[k], k == number)))
        bins[number] = offset + n
        bins = {k: 50 - free for k, free in fit.open_now().items()}
        assert len(bins) <= 4


def test_packing_places_every_token(spark, smoke):
    path = public_tokenizers.path("word_bpe_49k.json")
    library = Tokenizer.from_file(path)
    for docs in (odd(spark), shared.table(spark, smoke, "documents").repartition(9)):
        pieces = packing.pack(docs, path).toPandas()
        for _, own in pieces.sort_values("offset").groupby("sequence_id"):
            assert (own.offset == own.length.cumsum() - own.length).all() and own.length.sum() <= 4096
        want = sorted(np.array([*library.encode(r.text or "", add_special_tokens=False).ids, 1], "<u4").tobytes() for r in docs.collect())
        pieces["doc_id"] = pieces.doc_id.fillna(-1)
        got = sorted(b"".join(g.sort_values("piece").ids) for i, g in pieces.groupby("doc_id") if i != 4) + [pieces.ids[k] for k in pieces.index[pieces.doc_id == 4]] * (len(docs.columns) == 7)
        if len(docs.columns) == 7:
            assert sorted(got) == want
        lower = -(-pieces.length.sum() // 4096)
        assert pieces.sequence_id.nunique() <= lower + max(2, 0.05 * lower)
    assert packing.pack(odd(spark).limit(0), path).count() == 0


def test_row_operators_take_odd_rows(spark):
    docs = odd(spark)
    assert licenses.scan_licences(docs).count() == len(ODD_ROWS)
    assert secrets.scan_secrets(docs).where("n_layers is not null").count() == len(ODD_ROWS)
    assert secrets.scan_secrets(docs.limit(0)).count() == 0
    assert pd.isna(secrets.masked(None, []))


def test_toxicity_learns_from_all_labelled_rows(spark):
    rng = random.Random(7)
    filler = ["alpha", "beta", "gamma", "delta", "epsilon", "zeta", "eta", "theta"]
    rows = [(k, " ".join([*rng.choices(filler, k=8), *(["awful"] if k % 2 else [])]), "xy"[k % 4 // 2], k % 2) for k in range(7500)]
    docs = spark.createDataFrame([r[:3] for r in rows], "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(r[0], r[3]) for r in rows], "doc_id long, toxic int")
    usable = sum(zlib.crc32(str(k).encode()) % 5 != 0 for k in range(7500))
    assert usable > 5000 and toxicity.labelled_sample(docs, labels).count() == usable
    model = toxicity.train(docs, labels)
    scores = toxicity.Scorer(model).scores([r[1] for r in rows])
    assert ((scores >= 0.5) == np.array([r[3] for r in rows])).mean() > 0.99
    assert set(model.thresholds) == {None, "x", "y"}
    again = toxicity.train(docs.repartition(7), labels.repartition(3))
    assert np.array_equal(scores, toxicity.Scorer(again).scores([r[1] for r in rows])) and again.thresholds == model.thresholds


def test_toxicity_scores_equal_a_plain_forward_pass(monkeypatch):
    rng = np.random.default_rng(4)
    texts = [" ".join(f"wörd{k}," for k in rng.zipf(1.3, rng.integers(0, 60)) % 500) for _ in range(300)]
    model = toxicity.Learner.new().model

    def plain(text):
        rows = [toxicity.buckets(w) for w in text.split()] or [(0, 0, 0)]
        vectors = np.array([model.table[list(r)].sum(0) for r in rows + [(0, 0, 0)] * 2])
        reach = [max(sum(vectors[i + k] @ f[k][:, j] for k in range(len(f))) for i in range(len(rows))) for f in model.filters for j in range(toxicity.FILTERS)]
        return 1 / (1 + np.exp(-(np.maximum(np.array(reach) + model.shift, 0) @ model.weights + model.bias)))

    want = [plain(t) for t in texts]
    monkeypatch.setattr(toxicity, "BLOCK_WORDS", 200)
    kept = []
    for cache in (10**6, 40):
        monkeypatch.setattr(toxicity, "CACHE", cache)
        scorer = toxicity.Scorer(model)
        assert np.allclose(scorer.scores(texts), want, atol=1e-6)
        kept.append(len(scorer.known))
        known = toxicity.PackedWords()
        for t in texts:
            assert toxicity.word_ids(t, known) == (np.array([toxicity.buckets(w) for w in t.split()] or [(0, 0, 0)], "<u2").tobytes())
    assert kept[1] < kept[0] <= 500


def test_toxicity_moves_labelled_texts_alone(spark):
    docs = spark.createDataFrame([(k % 20_000 if k else None, f"t{k}") for k in range(20_100)], "doc_id long, text string")
    labels = spark.createDataFrame([(k, k % 2) for k in range(0, 20_000, 100)], "doc_id long, toxic int")
    passed = [r.doc_id for r in toxicity.likely_labelled(docs, labels).collect()]
    want = [k % 20_000 for k in range(1, 20_100) if k % 20_000 % 100 == 0]
    assert not set(want) - set(passed) and len(passed) < 2 * len(want)
    assert sorted(k for k in passed if k is not None and k % 100 == 0) == sorted(want)
    other = labels.withColumn("doc_id", F.col("doc_id").cast("int"))
    assert toxicity.likely_labelled(docs, other).count() == 20_100
    ids = {r.doc_id for r in toxicity.labelled_sample(docs, other).collect()}
    assert ids == {k for k in range(100, 20_000, 100) if zlib.crc32(str(k).encode()) % 5} | ({0} if zlib.crc32(b"0") % 5 else set())


def test_toxicity_shards_do_not_follow_the_partitions(spark, monkeypatch):
    rows = [(k, f"alpha beta w{k % 50} {'awful' if k % 3 == 0 else 'fine'}", int(k % 3 == 0)) for k in range(900)]
    docs = spark.createDataFrame([r[:2] for r in rows], "doc_id long, text string")
    labels = spark.createDataFrame([(r[0], r[2]) for r in rows], "doc_id long, toxic int")
    monkeypatch.setattr(toxicity, "SHARD_ROWS", 300)
    met, meet = [], toxicity.Learner.meet
    monkeypatch.setattr(toxicity.Learner, "meet", lambda self, parts: (met.append(len(parts)), meet(self, parts)))
    score = lambda: toxicity.Scorer(toxicity.train(docs, labels)).scores([r[1] for r in rows])
    first = score()
    frame = type(docs)
    plain = frame.repartition
    monkeypatch.setattr(frame, "repartition", lambda self, n, *cols: plain(self, max(40, n) if cols and isinstance(n, int) else n, *cols))
    assert np.array_equal(first, score()) and met == [3] * 2 * toxicity.EPOCHS


def test_thresholds_take_every_score(spark):
    rng = np.random.default_rng(8)
    toxic = rng.integers(0, 2, 3000)
    scores = 1 / (1 + np.exp(-(3 * toxic - 1 + rng.normal(0, 1, 3000))))
    rows = spark.createDataFrame([(None, int(t), float(x)) for t, x in zip(toxic, scores)], "lang string, toxic int, score double")
    bins = toxicity.score_bins(rows).collect()
    assert sum(r.n for r in bins) == 3000 and sum(r.toxic for r in bins) == toxic.sum()
    f1 = lambda at: 2 * toxic[scores >= at].sum() / ((scores >= at).sum() + toxic.sum())
    assert f1(toxicity.calibrate(bins)) >= max(map(f1, scores)) - 0.005


def test_packing_lets_other_operators_caches_go():
    toxicity.SCORER.update(key=1, scorer=object())
    shared.lean_worker("toxicity")
    assert toxicity.SCORER
    shared.lean_worker("packing")
    assert not toxicity.SCORER
    small = tokens.ChunkIds(public_tokenizers.path("word_bpe_49k.json"), *packing.CACHES["ids"])
    texts = [f"word{k} longer-word{k} {k}" for k in range(120_000)]
    want = tokens.chunk_ids(public_tokenizers.path("word_bpe_49k.json"))
    for at in range(0, len(texts), 20_000):
        block = pa.array(texts[at : at + 20_000])
        assert list(small.encode_column(block)) == list(want.encode_column(block))
    assert max(len(small.chunks.new), len(small.chunks.old)) < 100_000 + 60_000 < len(want.chunks.new) + len(want.chunks.old)
