"""Files that executors write and read below the shared folder, by its own URI."""

from vecengine.plans.folders import resolve  # noqa: F401
