"""Tables, gradient dumps and saved state."""

from gradsift.sources.state import collect_garbage, commit, discard, drop_iteration, read_state, shared_dir, write_metrics, write_state  # noqa: F401
from gradsift.sources.tables import TABLES, load, read_gradients, synthetic_gradients  # noqa: F401
