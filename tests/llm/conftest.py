import pytest

pytest.importorskip("adapterlab.llm")
