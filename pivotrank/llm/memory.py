"""Python workers outlive tasks; what a task has freed goes back to the machine when it ends."""

from __future__ import annotations

import ctypes
import functools
import gc

import pyarrow as pa

from .text import forget


def release() -> None:
    forget()
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except OSError:  # another C library
        pass


def trimmed(run):
    """A function over batches that releases memory after its last one."""

    @functools.wraps(run)
    def wrapped(source):
        yield from run(source)
        release()

    return wrapped


def trimmed_group(make):
    """A function over one group's table that releases memory after it."""

    def wrapped(table):
        try:
            return make(table)
        finally:
            release()

    return wrapped


def trimmed_pair(make):
    """The same over the tables of a cogroup."""

    def wrapped(left, right):
        try:
            return make(left, right)
        finally:
            release()

    return wrapped
