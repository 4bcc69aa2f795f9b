"""Deterministic harvest simulator: traces with known rows, states, trays and masses.

Everything is modular arithmetic on spark.range; there is no random state.
Carts work rows of their own from the middle outwards: they stop, harvest (the load
rises in a staircase), move on, and walk a full tray to the headland. Positions carry
noise, bursts shift a cart to the neighbouring row for a while, and loads have spikes.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Field:
    field_id: int = 0
    spacing: float = 1.63
    rows: int = 24
    length: float = 60.0


def _noise(salt: int, *cols: Column) -> Column:
    """Even in [-1, 1), the same in every run."""
    return F.pmod(F.xxhash64(*cols, F.lit(salt)), F.lit(20001)).cast("double") / 10000.0 - 1.0


def traces(spark: SparkSession, field: Field = Field(), carts: int = 6, sessions: int = 1, hz: float = 1.0, trays: int = 6, rate: float = 0.02, burst_share: float = 0.06, crew: bool = False, bias_share: float = 0.0, bias_part: float = 0.4, revisit_share: float = 0.0, gap_share: float = 0.0) -> DataFrame:
    """Samples with truth columns: truth_row, truth_state, truth_tray, truth_mass (net picked in the tray so far).

    A tray takes 4.25 kg. A cycle is picking (mass grows with distance along the row),
    then a walk to the headland and back with the empty tray. Each tray has a row of its own and sweeps it once.
    With ``crew`` neighbouring rows belong to different carts. In a ``bias_share`` of the trays positions lie one row off for the
    last ``bias_part`` of the picking; a ``revisit_share`` is picked from the middle to one end, then from the middle to the other; a
    ``gap_share`` of all stretches of 20 s is lost.
    """
    pick_s, walk_s = int(4.25 / rate), 30
    cycle = pick_s + walk_s
    n = int(trays * cycle * hz)
    base = spark.range(carts * sessions * n)
    i = F.col("id") % n
    who = F.floor(F.col("id") / n)
    df = base.select((who % carts).cast("long").alias("cart_id"), F.floor(who / carts).cast("int").alias("session"), (i / hz).alias("s"), i.alias("i"), F.col("id").alias("src_id"))
    tray, at = F.floor(F.col("s") / cycle).cast("long"), F.pmod(F.col("s"), F.lit(float(cycle)))
    picking = at < pick_s
    # Rows from the middle outwards, one block of rows per cart, so that no two carts share a row.
    slot = tray * carts + F.col("cart_id") if crew else F.col("cart_id") * trays + tray
    drawn = lambda salt, share, *cols: F.pmod(F.xxhash64("cart_id", "session", *cols, F.lit(salt)), F.lit(1000)) < int(share * 1000)
    middle = field.rows // 2
    row = F.when(slot % 2 == 0, middle + F.floor(slot / 2)).otherwise(middle - 1 - F.floor(slot / 2))
    row = F.pmod(row, F.lit(field.rows)).cast("int")
    up = (tray % 2) == 0
    # Stop, harvest, move: position advances in steps of 6 s, mass while standing.
    share = F.least(F.lit(1.0), at / pick_s)
    step = F.floor(at / 6) * 6 / pick_s
    way = F.when(up, step).otherwise(1 - step)
    way = F.when(drawn(21, revisit_share, tray), F.when(step < 0.5, 0.5 - step).otherwise(step)).otherwise(way)
    along = way * field.length * 0.9 + field.length * 0.05
    y = F.when(picking, along).otherwise(F.when(up, field.length + 3.0).otherwise(-3.0))
    burst = picking & (F.pmod(F.xxhash64("cart_id", "session", tray, F.floor(at / 20)), F.lit(1000)) < int(burst_share * 1000))
    lasting = picking & drawn(22, bias_share, tray) & (at >= (1 - bias_part) * pick_s)
    x = (row + F.when(burst, 0.8).otherwise(0.0) + F.when(lasting, 1.0).otherwise(0.0)) * field.spacing + 0.25 * field.spacing * _noise(1, F.col("src_id"))
    net = F.when(picking, share * 4.25).otherwise(0.0)
    spike = F.pmod(F.xxhash64("src_id", F.lit(5)), F.lit(100)) == 0
    w = 0.55 + net + F.when(spike, 2.5).otherwise(0.0) + 0.01 * _noise(2, F.col("src_id"))
    shake = F.when(picking, 0.2).otherwise(1.5)
    if gap_share:
        df = df.where(~drawn(23, gap_share, F.floor(F.col("s") / 20)))
    return df.select(
        F.lit(field.field_id).alias("field_id"), "session", "cart_id", (F.col("s") * 1e6).cast("long").alias("t_us"), x.alias("x"), (y + 0.3 * _noise(3, F.col("src_id"))).alias("y"), w.alias("w"),
        (shake * _noise(6, F.col("src_id"))).alias("ax"), (shake * _noise(7, F.col("src_id"))).alias("ay"), (shake * _noise(8, F.col("src_id"))).alias("az"),
        F.when(picking, "picking").otherwise("transport").alias("state"), "src_id", F.lit(field.spacing).alias("spacing"),
        row.alias("truth_row"), F.when(picking, "Pick").otherwise("NoPick").alias("truth_state"), tray.alias("truth_tray"), net.alias("truth_mass"),
    )


def truth_trays(sim: DataFrame) -> DataFrame:
    """cart_id, session, truth_tray, truth_row, gt: net mass of every tray."""
    return sim.where("truth_state = 'Pick'").groupBy("cart_id", "session", "truth_tray", "truth_row").agg(F.max("truth_mass").alias("gt"))
