"""Reference kernel on small states held in memory."""
