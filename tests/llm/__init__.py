"""A package, so that its modules may be named like those of the folder above; they import each other by bare names."""

import sys
from pathlib import Path

sys.path.insert(0, str(Path(__file__).parent))
