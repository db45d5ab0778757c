"""cubecast.plans"""
