"""The shared folder of the library, under the name that this subpackage uses."""

from segcube.sources.scratch import clean, materialised, new_folder, shared_root

__all__ = ["clean", "materialised", "new_folder", "shared_root"]
