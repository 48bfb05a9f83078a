import json

import pytest

from trajkit import cli


def test_settings_are_checked(tmp_path):
    f = tmp_path / "c.json"
    f.write_text(json.dumps({"samples": 2}))
    assert cli.config(str(f)).samples == 2
    f.write_text(json.dumps({"sampels": 2}))
    with pytest.raises(ValueError):
        cli.config(str(f))
    f.write_text(json.dumps({"partial_rollout": True, "correction": "none"}))
    with pytest.raises(ValueError):
        cli.config(str(f))


def test_queries_run_by_name(spark, small, tmp_path, capsys):
    assert cli.main(["list"]) == 0 and "loss_window" in capsys.readouterr().out
    assert cli.main(["loss_window", "--data", small, "--out", str(tmp_path / "out")]) == 0
    assert spark.read.parquet(str(tmp_path / "out")).count() == 1


def test_settings_reach_the_loop(spark, small, tmp_path, monkeypatch):
    from trajkit import catalog

    f, seen = tmp_path / "c.json", []
    f.write_text(json.dumps({"samples": 2}))
    monkeypatch.setitem(catalog.QUERIES, "train_loop", lambda s, d, cfg=None: seen.append(cfg) or s.range(1))
    assert cli.main(["train_loop", "--data", small, "--config", str(f), "--out", str(tmp_path / "o")]) == 0 and seen[0].samples == 2
    with pytest.raises(SystemExit):
        cli.main(["loss_window", "--config", str(f)])
