"""Path algebras and bit masks of snapshots."""
