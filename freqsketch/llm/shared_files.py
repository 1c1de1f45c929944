"""Binary files in the folder that driver and executors share, whatever store it is in."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyarrow import dataset, fs


def open_store(uri: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else f"file://{uri}")


@contextmanager
def atomic_writer(uri: str):
    """A stream whose file appears under its name once it is whole, so that a task that is
    run again, or twice at a time, leaves one good file."""
    store, path = open_store(uri)
    folder, name = path.rsplit("/", 1)
    store.create_dir(folder, recursive=True)
    draft = f"{folder}/_{name}.{uuid.uuid4().hex}"
    with store.open_output_stream(draft) as out:
        yield out
    store.move(draft, path)


def read_range(uri: str, offset: int, length: int) -> bytes:
    store, path = open_store(uri)
    with store.open_input_file(path) as f:
        return f.read_at(length, offset)


def read_whole(uri: str) -> bytes:
    store, path = open_store(uri)
    with store.open_input_file(path) as f:
        return f.read()


def read_groups(uri: str, column: str, values: list[str]) -> Iterator[dict]:
    """Rows of a Parquet table whose column has one of the values."""
    store, path = open_store(uri)
    table = dataset.dataset(path, format="parquet", filesystem=store)
    for b in table.to_batches(filter=dataset.field(column).isin(values), batch_size=4096):
        yield from b.to_pylist()


def sizes(uri: str) -> list[tuple[str, int]]:
    """(name, bytes) of the whole files of a folder, by name."""
    store, path = open_store(uri)
    found = store.get_file_info(fs.FileSelector(path, allow_not_found=True))
    return sorted((f.base_name, f.size) for f in found if f.is_file and not f.base_name.startswith(("_", ".")))
