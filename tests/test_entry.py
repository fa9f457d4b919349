import os
import shutil
import subprocess
import sys

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
COUNT = "import __spark_entry__ as e; q, s = e.queries(), e.oracle_sql(); print(len(q), len(s), sum(k.startswith('op') and k[2].isdigit() or k == 'pipeline' for k in q), set(s) <= set(q))"


def counted(folder):
    done = subprocess.run([sys.executable, "-c", COUNT], cwd=folder, capture_output=True, text=True, timeout=120)
    assert done.returncode == 0, done.stderr
    return done.stdout.split()


def test_library_stands_without_the_llm_folders(tmp_path):
    for name in ("corpuslab", "__spark_entry__.py", "corpus_pipeline.py"):
        src, to = os.path.join(ROOT, name), tmp_path / name
        if os.path.isdir(src):
            shutil.copytree(src, to, ignore=shutil.ignore_patterns("llm", "__pycache__"))
        elif os.path.exists(src):
            shutil.copy(src, to)
    assert not (tmp_path / "corpuslab" / "llm").exists()
    queries, _, llm, known = counted(tmp_path)
    assert int(queries) > 140 and llm == "0" and known == "True"
    (tmp_path / "corpus_pipeline.py").unlink(missing_ok=True)
    assert counted(tmp_path)[0] == queries


def test_an_error_inside_a_module_that_is_there_shows(tmp_path):
    shutil.copytree(os.path.join(ROOT, "corpuslab"), tmp_path / "corpuslab", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(os.path.join(ROOT, "__spark_entry__.py"), tmp_path)
    (tmp_path / "corpus_pipeline.py").write_text("import no_such_module_at_all")
    done = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; e.queries()"], cwd=tmp_path, capture_output=True, text=True, timeout=120)
    assert done.returncode and "no_such_module_at_all" in done.stderr
