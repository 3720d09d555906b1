"""A small purchases table with orders, buyers and items in layers."""

BUYERS = {"b1": ("Ann Roe", "555-01", 30), "b2": ("Bo Lind", "555-02", 30), "b3": ("Ann Roe", "555-03", 41), "b4": ("Ann Roe", "555-01", 30)}
ITEMS = {"p1": ("book", 15, 0.5), "p2": ("music", 11, None), "p3": ("book", 15, 0.5), "p4": ("toy", 15, 0.7), "p5": ("toy", 11, None)}
ORDERS = [
    (101, "b1", "d1", "web", "p1 p2"), (102, "b2", "d1", "app", "p2 p3"), (103, "b1", "d2", "web", "p1 p3"), (104, "b3", "d2", "web", "p1 p4"),
    (105, "b2", "d2", "web", "p1 p2 p5"), (106, "b3", "d3", "app", "p3 p4 p5"), (107, "b4", "d1", "app", "p2 p5"), (108, "b4", "d3", "web", "p1 p3"),
]
SCHEMA = "ord int, item string, buyer string, day string, channel string, buyer_name string, phone string, age int, kind string, price int, weight double, ship_cost double"


def rows(dirty=False):
    out = []
    for ord_, buyer, day, channel, items in ORDERS:
        for item in items.split():
            kind, price, weight = ITEMS[item]
            out.append((ord_, item, buyer, day, channel, *BUYERS[buyer], kind, price, weight, None if weight is None else weight + 4))
    if dirty:
        last = next(r for r in out if r[:2] == (104, "p4"))
        out.append((*last[:9], 12, *last[10:]))
    return out


def purchases(spark, dirty=False):
    return spark.createDataFrame(rows(dirty), SCHEMA)
