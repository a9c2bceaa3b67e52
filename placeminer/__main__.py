"""``python -m placeminer discover|experiment|batch``."""

from __future__ import annotations

import argparse
import json
from dataclasses import replace
from pathlib import Path

from pyspark.sql import SparkSession


def main(argv: list[str] | None = None) -> int:
    from .operators import model
    from .plans.config import PRESETS, Config
    from .plans.experiment import grid
    from .plans.run import RUNS, prepare, run
    from .sources.io import write_net, write_table
    from .sources.logs import LOGS, events

    parser = argparse.ArgumentParser(prog="placeminer")
    parser.add_argument("command", choices=["discover", "experiment", "batch"])
    parser.add_argument("--data", required=True, help="folder of the input tables")
    parser.add_argument("--log", choices=sorted(LOGS), default="conv")
    parser.add_argument("--config", help="JSON configuration; for batch a JSON list of them")
    parser.add_argument("--preset", choices=sorted(PRESETS), default="base")
    parser.add_argument("--tau", type=float)
    parser.add_argument("--depth", type=int)
    parser.add_argument("--out", required=True, help="folder for results")
    a = parser.parse_args(argv)
    spark = SparkSession.builder.appName("placeminer").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    config = Config.load(a.config) if a.config and a.command != "batch" else replace(PRESETS[a.preset], log=a.log)
    config = replace(config, **{k: v for k, v in (("tau", a.tau), ("max_depth", a.depth)) if v is not None})
    out = Path(a.out)
    out.mkdir(parents=True, exist_ok=True)
    if a.command == "batch":
        settings = [Config.from_json(json.dumps(c)) for c in json.loads(Path(a.config).read_text())]
        rows = [run(c, prepare(events(spark, a.data, c.log), c.order, c.seed)).row() for c in settings]
        write_table(spark.createDataFrame([tuple(r.values()) for r in rows], RUNS), str(out / "runs"))
        return 0
    p = prepare(events(spark, a.data, config.log), config.order, config.seed)
    if a.command == "discover":
        found = run(config, p, quality=False)
        net = model.to_net(found.names(), p.labels)
        for kind in ("pnml", "dot", "json"):
            write_net(net, str(out / f"net.{kind}"), json.loads(config.to_json()))
        config.save(str(out / "config.json"))
        print(model.describe(net))
        return 0
    found = run(config, p)
    write_table(found.discovery.supervisor.event_table(spark), str(out / "events"))
    write_table(found.discovery.supervisor.timing_table(spark), str(out / "timings"))
    write_table(grid(p, config, depths=range(2, config.max_depth + 1)), str(out / "runs"))
    config.save(str(out / "config.json"))
    print(json.dumps(found.row()))
    return 0


if __name__ == "__main__":
    raise SystemExit(main())
