import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parents[1]


def run(code: str) -> str:
    return subprocess.run([sys.executable, "-c", code], cwd=ROOT, capture_output=True, text=True, check=True).stdout.strip()


def test_sorts_stay_without_what_the_other_operators_import():
    block = "import sys\nfor x in ('xxhash', 'tiktoken', 'hybridsort.llm', 'corpus_pipeline'):\n    sys.modules[x] = None\n"
    names = run(block + "import __spark_entry__ as e\nprint(*e.queries())").split()
    assert "msd_sort_uniform" in names and not any(n.startswith("op") and n[2].isdigit() for n in names)


def test_every_sql_has_its_query():
    assert run("import __spark_entry__ as e\nprint(set(e.oracle_sql()) - set(e.queries()))") == "set()"


def test_no_folder_of_one_machine_on_a_cluster():
    from hybridsort.sources import tables

    class Conf:
        def get(self, *_):
            return None

    class Context:
        master, applicationId = "spark://host:7077", "app"

        def getConf(self):
            return Conf()

    class Session:
        conf, sparkContext = Conf(), Context()

    import pytest

    with pytest.raises(RuntimeError):
        tables.shared_dir(Session())
