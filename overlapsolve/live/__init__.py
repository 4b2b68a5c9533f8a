"""Free-running tasks that exchange slabs through a mailbox."""
