import pytest
from pyspark.sql import functions as F

from dedupflow.functions import groups, hashing
from dedupflow.operators import tags


def test_published_encodings_of_the_curve():
    r = groups.Ristretto
    y = 4 * pow(5, -1, groups.P25519) % groups.P25519
    _, x = groups._root_of_ratio((y * y - 1) % groups.P25519, (groups.D25519 * y * y + 1) % groups.P25519)
    base = (x, y, 1, x * y % groups.P25519)
    assert r.encode(r.identity) == bytes(32)
    assert r.encode(base).hex() == "e2f2ae0a6abc4e71a884a961c500515f58e30b6aa582dd8db6a65945e08d2d76"
    assert r.encode(r.power(base, 2)).hex() == "6a493210f7499cd17fecb510ae0cea23a110e8d5b901f8acadd3095c73a3b919"
    assert r.encode(r.power(base, r.q)) == bytes(32)
    with pytest.raises(ValueError):
        r.decode(b"\xff" * 32)


def test_prime_group():
    g = groups.group("modp2048")
    assert g.p.bit_length() == 2048 and len(g.encode(g.hash_to(b"a")).hex()) == 512
    assert pow(3, g.p - 1, g.p) == 1 and pow(g.hash_to(b"a"), g.q, g.p) == 1


@pytest.mark.parametrize("library", [True, False])
def test_powers_by_the_library_equal_integers(library, monkeypatch):
    if not library:
        monkeypatch.setattr(groups, "_libcrypto", lambda: None)
    p, h = groups.group("modp2048").p, groups.group("modp2048").hash_to(b"a")
    for element in (0, 1, 2, h, p - 1):
        for k in (1, 2, 3, (1 << 256) - 1, p // 2, p - 2):
            assert groups.power_mod(element, k, p) == pow(element, k, p)
    assert groups.power_mod(h, 0, p) == 1 and groups.power_mod(h, -1, p) == pow(h, -1, p)


@pytest.mark.parametrize("scheme", tags.OBLIVIOUS)
def test_three_steps_equal_the_direct_power(scheme):
    authority, own = tags.Authority.create(scheme, seed=1), groups.group(scheme)
    sent = set()
    for text in (b"a", b"b", b"a"):
        blinded, r = tags.blind(text, own)
        assert 1 <= r < own.q
        sent.add(blinded)
        assert tags.unblind(tags.evaluate(blinded, authority), r, own) == tags.direct(text, authority)
    assert len(sent) == 3  # equal texts look different on the way
    assert tags.direct(b"a", authority) != tags.direct(b"b", authority)
    assert tags.direct(b"a", authority) != tags.direct(b"a", authority.at(1))


def test_secret_stays_out_of_sight():
    authority = tags.Authority.create("keyed")
    assert authority._secret.hex() not in repr(authority) and "_secret" not in repr(authority)
    with pytest.raises(ValueError):
        tags.Authority.create("keyed", bits=64)
    with pytest.raises(ValueError):
        tags.Authority.create("nothing")


def test_items_with_nulls_blanks_and_copies(spark):
    rows = [(1, 1, "x"), (1, 2, "x"), (2, 3, "x"), (1, 4, ""), (1, 5, None), (2, 6, "é")]
    items = spark.createDataFrame(rows, "sid long, item_id long, content string")
    got = {(r.sid, r.item_id): r.copies for r in tags.protect(items).collect()}
    assert got == {(1, 1): 2, (2, 3): 1, (1, 4): 1, (2, 6): 1}
    assert tags.protect(items, tags.Authority.create("keyed", seed=2)).select("tag").distinct().count() == 3
    assert tags.protect(items.limit(0)).count() == 0


def test_normalisation_is_opt_in(spark):
    df = spark.createDataFrame([("A  b ",), ("a b",)], "content string")
    n = lambda how: df.select(hashing.content_hash(F.col("content"), how).alias("h")).distinct().count()
    assert (n("none"), n("trim"), n("space"), n("case")) == (2, 2, 2, 1)


def test_toy_columns_equal_integers(spark):
    df = spark.createDataFrame([(7, 123456), (groups.TOY_P - 2, groups.TOY_Q - 1)], "b long, e long")
    for r in df.withColumn("p", hashing.toy_power(F.col("b"), F.col("e"))).collect():
        assert r.p == pow(r.b, r.e, groups.TOY_P)


def test_fnv_vectors():
    import pandas as pd

    got = hashing.fnv1a64_of(pd.Series(["", "a", "foobar"]))
    assert [v % 2**64 for v in got] == [0xCBF29CE484222325, 0xAF63DC4C8601EC8C, 0x85944171F73967E8]


def test_order_keys_agree(spark):
    df = spark.range(200).select((F.col("id") * 7 % 50).alias("s"), (F.col("id") * 13 % 90).alias("q"), (F.col("id") % 20).alias("c"))
    rows = df.select("s", "q", "c", hashing.order_key(F.col("s"), F.col("q"), F.col("c")).alias("n"), hashing.wide_order_key(F.col("s"), F.col("q"), F.col("c")).alias("w")).collect()
    expected = sorted((r.s, r.q, r.c) for r in rows)
    assert [(r.s, r.q, r.c) for r in sorted(rows, key=lambda r: r.n)] == expected == [(r.s, r.q, r.c) for r in sorted(rows, key=lambda r: r.w)]
    with pytest.raises(ValueError):
        hashing.order_key(F.col("s"), F.col("q"), F.col("c"), 10**12, 10**6)
