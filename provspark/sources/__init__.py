"""Item carriers, readers and writers."""
