"""Runs array kernels on whole images: one shuffle by image, one image in a task at a time."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame

CELLS = "image_id long, row int, col int"


def frame_of(rows: np.ndarray, cols: np.ndarray, margin: int) -> tuple[int, int, int, int]:
    """First row and column, height and width of the padded frame. It starts at even coordinates, so that the parity
    subfields are those of the plane whatever the margin."""
    r0, c0 = (int(x.min()) - margin - (int(x.min()) - margin) % 2 for x in (rows, cols))
    return r0, c0, int(rows.max()) + margin + 1 - r0, int(cols.max()) + margin + 1 - c0


def raster(table, margin: int, columns: dict[str, tuple]) -> tuple[int, int, int, dict[str, np.ndarray]]:
    """An Arrow table of cells as arrays over its padded frame: image, first row, first column, arrays by name.

    ``columns`` gives each array's column, type and fill; a column None marks all cells of the table."""
    rows, cols = table.column("row").to_numpy(), table.column("col").to_numpy()
    r0, c0, h, w = frame_of(rows, cols, margin)
    out = {}
    for name, (column, kind, fill) in columns.items():
        array = np.full((h, w), fill, kind)
        array[rows - r0, cols - c0] = True if column is None else table.column(column).to_numpy(zero_copy_only=False)
        out[name] = array
    return table.column("image_id")[0].as_py(), r0, c0, out


def cell_table(image: int, r0: int, c0: int, where: np.ndarray, extra: dict[str, np.ndarray] | None = None):
    """The true cells of ``where`` as an Arrow table, with the values of ``extra`` arrays."""
    import pyarrow as pa

    rows, cols = np.nonzero(where)
    columns = {"image_id": pa.array(np.full(len(rows), image, np.int64)), "row": pa.array((rows + r0).astype(np.int32)), "col": pa.array((cols + c0).astype(np.int32))}
    for name, values in (extra or {}).items():
        columns[name] = pa.array(values[rows, cols])
    return pa.table(columns)


def per_image(px: DataFrame, task: Callable, schema: str) -> DataFrame:
    """``task`` maps the Arrow table of one image to one of the result."""
    return px.groupBy("image_id").applyInArrow(task, schema)


def transform(px: DataFrame, operate: Callable[[np.ndarray], np.ndarray], margin: int = 0) -> DataFrame:
    """Applies a boolean array operator to each image of dense pixels (or points): the object cells of the result."""

    def task(table):
        columns = {"x": ("obj" if "obj" in table.column_names else None, bool, False)}
        image, r0, c0, arrays = raster(table, margin, columns)
        return cell_table(image, r0, c0, operate(arrays["x"]))

    return per_image(px, task, CELLS)
